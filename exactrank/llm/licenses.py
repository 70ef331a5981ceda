"""License scan by diagonal voting, all in DataFrame operations.

Texts and templates are word sequences. Templates are the parts of public licence texts. Every run
of ``GRAM`` words of a text that also stands in a template votes for the diagonal (text position
minus template position); short phrases vote by pairs of words. The join compares hash and
words, so a vote is exact. Votes are counted by diagonal, and neighbouring diagonals (words
inserted or lost) are merged. Then the span is verified: along the text, the votes are chained
as long as their places in the template rise, and the chain's share of the template's runs
decides. A phrase counts where one diagonal holds all its pairs, which is the phrase itself.
Templates are a fixed list, some thousand rows, and are broadcast: text words are never
shuffled, only votes.

Defined results: a null text is empty (no words, no labels, score 0, null places); rows that
repeat both doc_id and text give the same result each; a null doc_id is kept; other columns
of the input are ignored.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from exactrank.llm.common import documents
from exactrank.llm.license_texts import TEXTS

#: Words are runs of anything but these.
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"

# Phrases whose exact places are reported, with their labels.
PHRASES = [
    ("gnu general public license", "gpl"),
    ("apache license", "apache"),
    ("cc by", "cc-by"),
    ("mit license", "mit"),
]
#: Words of a template's runs.
GRAM = 5
#: A template's label is given from this share of its runs on: one changed word spoils five.
MIN_SHARE = 0.6
#: Diagonals at most so far apart are one alignment.
NEAR_DIAGONALS = 8
_WORD = re.compile("[a-z0-9]+")


def template_parts(texts=TEXTS) -> list[tuple[str, str]]:
    """(words, label) of every part of at least GRAM words."""
    parts = [(_WORD.findall(part.lower()), label) for label, text in texts for part in text.split("\n\n")]
    return [(" ".join(words), label) for words, label in parts if len(words) >= GRAM]


TEMPLATES = template_parts()


def lowered(text: Column) -> Column:
    """A-Z in lower case. The Kelvin sign is the one other letter whose lower case is in
    a-z; another non-ASCII letter takes its place, which leaves word bounds as they are."""
    return F.lower(F.replace(F.coalesce(text, F.lit("")), F.lit("K"), F.lit("ÿ")))


def words_of(text: Column) -> Column:
    return F.filter(F.split(lowered(text), SEPARATORS), lambda w: w != "")


def template_runs(phrases, templates) -> list[tuple]:
    """(template, label, phrase, runs, length, at, gram) of every run of words that may vote."""
    rows = []
    for t, (text, label) in enumerate([*phrases, *templates]):
        words, phrase = text.split(" "), t < len(phrases)
        n = 2 if phrase else GRAM
        grams = [" ".join(words[i : i + n]) for i in range(len(words) - n + 1)]
        rows += [(t, label, phrase, len(grams), n, i, g) for i, g in enumerate(grams)]
    return rows


def _matches(spark: SparkSession, rows: list[tuple], length: int, names: list[str]) -> DataFrame:
    """By the words of a run, where it stands: one row a run, so that a join makes no copies."""
    made = spark.createDataFrame([(*r[:4], r[5], *r[6].split(" ")) for r in rows if r[4] == length], "template int, label string, phrase boolean, runs int, at int, " + ", ".join(f"{n} string" for n in names[:length]))
    return made.groupBy(*names[:length]).agg(F.collect_list(F.struct("template", "label", "phrase", "runs", "at")).alias(f"m{length}"))


def scan_licenses(docs: DataFrame, phrases=PHRASES, templates=TEMPLATES, min_share: float = MIN_SHARE) -> DataFrame:
    """One row per row of ``docs(doc_id, text)``: doc_id, n_words, n_base, first_word,
    last_word, base_labels, labels, score, spans (of every accepted alignment)."""
    spark, names = docs.sparkSession, [f"a{i}" for i in range(GRAM)]
    rows = docs.select("doc_id", F.xxhash64(F.coalesce("text", F.lit(""))).alias("th"), words_of(F.col("text")).alias("w"))
    shifted = [F.col("w").alias("a0"), *[F.expr(f"slice(w, {i + 1}, greatest(size(w) - {i}, 0))").alias(f"a{i}") for i in range(1, GRAM)]]
    words = rows.select("doc_id", "th", F.posexplode(F.arrays_zip(*shifted)).alias("pos", "p")).select("doc_id", "th", "pos", *[F.col(f"p.{n}").alias(n) for n in names])
    runs = template_runs(phrases, templates)
    matched = words
    for length in (2, GRAM):
        table = F.broadcast(_matches(spark, runs, length, names))
        matched = matched.join(table, names[:length], "left")
    nothing = F.array().cast("array<struct<template:int,label:string,phrase:boolean,runs:int,at:int>>")
    votes = (
        matched.where(F.col("m2").isNotNull() | F.col(f"m{GRAM}").isNotNull())
        .select("doc_id", "th", "pos", F.explode(F.concat(F.coalesce("m2", nothing), F.coalesce(f"m{GRAM}", nothing))).alias("m")).select("doc_id", "th", "pos", "m.*")
    )
    key = ["doc_id", "th", "template", "label", "phrase", "runs"]
    # Rows that repeat id and text vote twice for the same: sets, not lists.
    diagonals = votes.groupBy(*key, (F.col("pos") - F.col("at")).alias("diag")).agg(F.collect_set(F.struct("pos", "at")).alias("hits"))
    along = Window.partitionBy("doc_id", "th", "template").orderBy("diag")
    apart = F.col("diag") - F.lag("diag").over(along)
    # A phrase is exact or not there, so its diagonals stay apart.
    fresh = (F.coalesce(apart, F.lit(NEAR_DIAGONALS + 1)) > NEAR_DIAGONALS) | F.col("phrase")
    numbered = diagonals.withColumn("run", F.sum(fresh.cast("int")).over(along.rowsBetween(Window.unboundedPreceding, 0)))
    gathered = numbered.groupBy(*key, "run").agg(F.min("diag").alias("diag"), F.array_sort(F.flatten(F.collect_list("hits"))).alias("hits"))
    # The chain: from the first vote on, each next one further on in the template.
    start = F.struct(F.lit(-1).alias("at"), F.lit(0).alias("n"), F.lit(-1).alias("end"))
    rises = lambda c, h: F.when(h["at"] > c["at"], F.struct(h["at"].alias("at"), (c["n"] + 1).alias("n"), h["pos"].alias("end"))).otherwise(c)
    spans = gathered.withColumn("chain", F.aggregate("hits", start, rises)).select(
        *key, F.when(F.col("phrase"), F.col("diag")).otherwise(F.col("hits")[0]["pos"]).alias("start"),
        (F.col("chain.end") + F.when(F.col("phrase"), 1).otherwise(GRAM - 1)).alias("end"), F.col("chain.n").alias("hit"),
    ).withColumn("share", F.col("hit") / F.col("runs"))
    full = F.col("phrase") & (F.col("hit") == F.col("runs"))
    accepted = full | (~F.col("phrase") & (F.col("share") >= min_share))

    def joined(when: Column) -> Column:
        return F.array_join(F.array_sort(F.collect_set(F.when(when, F.col("label")))), ",")

    found = spans.groupBy(F.col("doc_id").alias("_d"), F.col("th").alias("_t")).agg(
        F.count_if(full).alias("n_base"),
        F.min(F.when(full, F.col("start"))).alias("first_word"),
        F.max(F.when(full, F.col("start"))).alias("last_word"),
        joined(full).alias("base_labels"),
        joined(accepted).alias("labels"),
        F.max(F.when(~F.col("phrase") | full, F.col("share"))).alias("score"),
        F.array_sort(F.collect_list(F.when(accepted, F.struct("start", "end", "label", "share")))).alias("spans"),
    )
    counted = rows.select("doc_id", "th", F.size("w").cast("long").alias("n_words"))
    # At most a span or so for each licensed document, but their number follows the corpus:
    # the planner picks the join.
    return counted.join(found, counted["doc_id"].eqNullSafe(found["_d"]) & (counted["th"] == found["_t"]), "left").select(
        "doc_id",
        "n_words",
        F.coalesce("n_base", F.lit(0)).cast("long").alias("n_base"),
        F.col("first_word").cast("long").alias("first_word"),
        F.col("last_word").cast("long").alias("last_word"),
        F.coalesce("base_labels", F.lit("")).alias("base_labels"),
        F.coalesce("labels", F.lit("")).alias("labels"),
        F.coalesce("score", F.lit(0.0)).alias("score"),
        "spans",
    )


def op7_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(documents(spark, sf_dir, "doc_id", "text")).drop("spans")


def _sql() -> str:
    values = [f"({t}, '{label}', {str(phrase).lower()}, {runs}, {n}, {at}, '{gram}')" for t, label, phrase, runs, n, at, gram in template_runs(PHRASES, TEMPLATES)]
    return rf"""
WITH runs(template, label, phrase, runs, n, k, gram) AS (VALUES {', '.join(values)}),
d AS (SELECT row_number() OVER () AS rid, doc_id,
  list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{SEPARATORS}'), lambda x: x <> '') AS w
  FROM documents),
p AS (SELECT rid, w, unnest(range(len(w))) AS pos FROM d),
g AS (SELECT rid, pos, 2 AS n, array_to_string(w[pos + 1:pos + 2], ' ') AS gram FROM p
  UNION ALL SELECT rid, pos, {GRAM}, array_to_string(w[pos + 1:pos + {GRAM}], ' ') FROM p),
v AS (SELECT rid, template, label, phrase, runs, pos, k, pos - k AS diag FROM g JOIN runs USING (n, gram)),
x AS (SELECT rid, template, diag, any_value(phrase) AS phrase FROM v GROUP BY ALL),
f AS (SELECT *, CASE WHEN phrase OR coalesce(diag - lag(diag) OVER (PARTITION BY rid, template ORDER BY diag), 99) > {NEAR_DIAGONALS} THEN 1 ELSE 0 END AS fresh FROM x),
r AS (SELECT *, sum(fresh) OVER (PARTITION BY rid, template ORDER BY diag) AS run FROM f),
h AS (SELECT v.rid, v.template, v.label, v.phrase, v.runs, r.run, min(v.diag) AS start, list(v.k ORDER BY v.pos, v.k) AS places
  FROM v JOIN r ON v.rid = r.rid AND v.template = r.template AND v.diag = r.diag GROUP BY ALL),
s AS (SELECT *, list_reduce(list_prepend({{'at': -1, 'n': 0}}, list_transform(places, lambda y: {{'at': y, 'n': 0}})),
  lambda c, y: CASE WHEN y.at > c.at THEN {{'at': y.at, 'n': c.n + 1}} ELSE c END).n AS hit FROM h),
m AS (SELECT *, phrase AND hit = runs AS exact, hit::DOUBLE / runs AS share FROM s),
o AS (SELECT rid, count(*) FILTER (exact) AS n_base, min(start) FILTER (exact) AS first_word, max(start) FILTER (exact) AS last_word,
  string_agg(DISTINCT label, ',' ORDER BY label) FILTER (exact) AS base_labels,
  string_agg(DISTINCT label, ',' ORDER BY label) FILTER (exact OR (NOT phrase AND share >= {MIN_SHARE})) AS labels,
  max(share) FILTER (NOT phrase OR exact) AS score FROM m GROUP BY rid)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_base, 0)::BIGINT AS n_base, first_word::BIGINT AS first_word,
  last_word::BIGINT AS last_word, coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels,
  coalesce(score, 0)::DOUBLE AS score
FROM d LEFT JOIN o USING (rid)
"""


OP7_SQL = _sql()
