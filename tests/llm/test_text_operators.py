"""Fingerprints and quality rules against plain Python on the whole small table and on edge rows."""

import hashlib
import re

import duckdb
from pyspark.sql import functions as F

from exactrank.llm import quality, syncmers

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, slice int, guest string"
EDGES = [(1, None, 1, "x"), (2, "", 2, "x"), (3, "a", 3, "x"), (3, "a", 3, "x"), (4, "é ñ\n" * 9, 4, "x"), (5, "ab cd " * 40000, 5, "x"), (None, "null id", 6, "x"), (7, "Und " * 300, 7, "x")]
SPACES = "\t\n\x0b\x0c\r "


def all_texts():
    return duckdb.connect().execute(f"select doc_id, text from '{SF}/documents.parquet'").fetchall()


def plain_counts(text):
    text = text or ""
    words = re.findall(rf"[^{SPACES}]+", text)
    seen, dup = set(), 0
    for line in text.split("\n"):
        if re.search(rf"[^{SPACES}]", line):
            dup += line in seen
            seen.add(line)
    at = {}
    for i in range(len(words) - 4):
        at.setdefault(tuple(words[i : i + 5]), []).append(i)
    covered = {j for v in at.values() if len(v) > 1 for i in v for j in range(i, i + 5)}
    failed = len(words) < 10 or 100 * len(covered) > 20 * len(words)
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), dup, len(covered), failed


def check_counts(spark, rows, df, verdict=None):
    got = sorted(map(str, ((r["doc_id"], *(r[c] for c in quality._COUNTS), r["base_failed"]) for r in quality.assess_quality(df, verdict).collect())))
    assert got == sorted(map(str, ((d, *plain_counts(t)) for d, t in rows)))


def test_rule_counts_equal_plain_python(spark):
    check_counts(spark, all_texts(), spark.read.parquet(f"{SF}/documents.parquet"))
    check_counts(spark, [r[:2] for r in EDGES], spark.createDataFrame(EDGES, SCHEMA))
    assert quality.assess_quality(spark.createDataFrame([], SCHEMA), None).count() == 0


def test_classifier_on_rows_it_has_not_seen(spark):
    sf = SF.replace("0.001", "0.1")
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    seen = labels.where("doc_id % 2 = 0")
    verdict = quality.train(docs, seen, 1000)
    apart = labels.where("doc_id % 2 = 1").join(quality.assess_quality(docs, verdict), "doc_id").where("not base_failed")
    good, bad = (apart.where(f"quality = {q}").agg(F.avg(F.col("kept").cast("double"))).first()[0] for q in (1, 0))
    assert good > 0.98 and bad < 0.1
    assert quality.train(docs, labels.where("quality = 1"), 50) is None
    kept = quality.keep_good(docs, verdict)
    assert kept.columns == docs.columns and 0 < kept.count() < docs.count()


def test_fingerprints_of_neighbours(spark):
    def expect(rows):
        rows = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0), (r[1] is not None, r[1])))
        return [(d, len(t or ""), hashlib.sha256(syncmers.edited(t or "", rows[(i + 1) % len(rows)][1] or "").encode()).hexdigest()) for i, (d, t) in enumerate(rows)]

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for rows, df in ((all_texts(), docs), ([r[:2] for r in EDGES], spark.createDataFrame(EDGES, SCHEMA)), ([(1, "one alone")], spark.createDataFrame([(1, "one alone")], "doc_id long, text string"))):
        out = syncmers.fingerprint_neighbours(df, 5).collect()
        assert sorted(map(str, ((r["doc_id"], r["n_chars"], r["edited_sha256"]) for r in out))) == sorted(map(str, expect(rows)))
        by_text = {}
        texts = dict(rows)
        for r in out:
            assert by_text.setdefault(texts[r["doc_id"]] or "", r["fingerprint"]) == r["fingerprint"]
            assert 0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1
    assert syncmers.fingerprint_neighbours(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    big = [r for r in syncmers.fingerprint_neighbours(docs).collect() if r["n_chars"] > 600]
    near = sorted(r["near_edited"] for r in big)
    assert near[len(near) // 10] > 0.5 and sum(r["near_next"] < 0.2 for r in big) > 0.9 * len(big)


def test_an_anchor_does_not_depend_on_its_surroundings():
    import numpy as np

    word = np.frombuffer(b"some words that stand in two quite different places", np.uint8)
    a, b = (np.concatenate([np.frombuffer(p, np.uint8), word]) for p in (b"first: ", b"another start: "))
    assert {h for p, h in zip(*syncmers.syncmers(a)) if p >= 7} == {h for p, h in zip(*syncmers.syncmers(b)) if p >= 15}
    s = syncmers.sketches([bytes(a)])[0]
    assert syncmers.likeness(s, syncmers.from_string(syncmers.to_string(s))) == 1


def test_likeness_of_long_near_copies():
    import random

    draw = random.Random(1)
    words = ["".join(draw.choices("abcdefghijklmnopqrstuvwxyz", k=draw.randint(2, 9))) for _ in range(40_000)]

    def like(a, b):
        return syncmers.likeness(*syncmers.sketches([" ".join(a).encode(), " ".join(b).encode()]))

    for n in (1000, 10_000, 40_000):  # edits spread over the text
        assert like(words[:n], [w for i, w in enumerate(words[:n]) if i % 50]) > 0.85, n
    text, more = words[:2000], words[3000:3200]  # one paragraph of over 256 bytes set in the middle
    assert like(text, text[:1000] + more + text[1000:]) > 0.85
    assert like(text, text[1000:] + text[:1000]) < 0.75  # out of order: one half counts
    assert like(text, words[5000:7000]) < 0.1
