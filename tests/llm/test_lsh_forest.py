"""Similarity classes and link counts against all pairs in plain Python."""

import random

import numpy as np
from pyspark.sql import functions as F

from exactrank.llm import lsh_forest as lf

SCHEMA = "doc_id long, text string, component long, rk string"


def brute(rows):
    def parts(text):
        w = (text or "").split()
        if not w:
            return {("bare", text or "")}
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))}

    sets = [parts(t) for _, t in rows]
    near = [[j for j in range(len(rows)) if j != i and 10 * len(sets[i] & sets[j]) >= 8 * len(sets[i] | sets[j])] for i in range(len(rows))]
    group = list(range(len(rows)))
    for _ in rows:
        group = [min([group[i], *(group[j] for j in near[i])]) for i in range(len(rows))]
    ids = {}
    for (d, _), g in zip(rows, group):
        ids[g] = min(ids.get(g) if ids.get(g) is not None else d or 0, d) if d is not None else ids.get(g)
    return sorted(map(str, ((d, ids[g], len(n)) for (d, _), g, n in zip(rows, group, near))))


def run(spark, rows):
    out = lf.near_duplicates(spark.createDataFrame([(d, t, 1, "x") for d, t in rows], SCHEMA)).collect()
    return sorted(str((r["doc_id"], r["class_id"], r["n_links"])) for r in out)


def test_edge_rows_and_dense_classes(spark, monkeypatch):
    rng = random.Random(5)
    rows = [(1, None), (2, ""), (3, " "), (4, "two words"), (5, "two words"), (5, "two words"), (None, "no id at all here"), (6, "long " * 30000)]
    base = [f"w{i}" for i in range(120)]
    for i in range(60):
        own = list(base)
        for at in rng.sample(range(120), rng.randrange(1, 5)):
            own[at] = f"x{rng.randrange(10**6)}"
        rows.append((100 + i, " ".join(own)))
    rows += [(300 + i, " ".join(f"u{rng.randrange(10**6)}" for _ in range(50))) for i in range(30)]
    monkeypatch.setattr(lf, "TILE", 16)  # several tiles a class
    assert run(spark, rows) == brute(rows)


def test_empty_table_and_what_stays(spark):
    empty = spark.createDataFrame([], SCHEMA)
    assert lf.near_duplicates(empty).count() == 0
    docs = spark.createDataFrame([(3, "a b c d e f", 0, "p"), (2, "a b c d e f", 1, "q"), (2, "a b c d e f", 1, "q"), (9, "other text", 2, "r"), (None, None, 3, "s")], SCHEMA)
    kept = sorted(map(str, map(tuple, lf.one_of_each_class(docs).collect())))
    assert kept == sorted(map(str, [(2, "a b c d e f", 1, "q"), (9, "other text", 2, "r"), (None, None, 3, "s")]))


def family(rng, n, words, edits):
    base = [f"w{i}" for i in range(words)]
    out = []
    for i in range(n):
        own = list(base)
        for at in rng.sample(range(words), rng.choice(edits)):
            own[at] = f"x{rng.randrange(10**6)}"
        out.append(" ".join(own))
    return out


def exact(texts):
    """(class as least row, links) of each text, by the product of the incidence matrix with itself."""
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in (t.split() for t in texts)]
    number = {g: i for i, g in enumerate(sorted(set().union(*sets)))}
    there = np.zeros((len(sets), len(number)), np.float32)
    for i, s in enumerate(sets):
        there[i, [number[g] for g in s]] = 1
    common = (there @ there.T).round().astype(np.int64)
    size = np.diag(common)
    near = 10 * common >= 8 * (size[:, None] + size[None] - common)
    np.fill_diagonal(near, False)
    group = np.arange(len(sets))
    for _ in range(100):
        least = np.minimum(group, np.where(near, group[None], len(group)).min(1))
        if (least == group).all():
            break
        group = least
    return group.tolist(), near.sum(1).tolist()


def test_prefixes_shorten_only_where_the_recall_is_short(spark):
    rng = random.Random(2)
    crowd = family(rng, 300, 100, range(1, 4))
    lone = [" ".join(f"u{rng.randrange(10**6)}" for _ in range(60)) for _ in range(50)]
    docs = spark.createDataFrame(list(enumerate(crowd + lone)), "doc_id long, text string").withColumn("rk", F.col("doc_id"))
    nodes = docs.mapInArrow(lf._sketch_rows, "doc_id long, rk long, node binary, sig binary, sketch binary").cache()
    rows = lf.matched_prefixes(nodes.select("node", "sig", "sketch"), 32).join(nodes.select("node", "doc_id"), "node").toPandas()
    depths = {d: sorted(g["depth"]) for d, g in rows.groupby("doc_id")}
    assert all(len(x) == lf.TREES for x in depths.values())
    # Every text reaches the recall, in the crowd by going up from where the runs were small enough.
    assert min(lf.surely_met(x) for x in depths.values()) >= lf.RECALL
    assert all(set(depths[i]) == {lf.SHALLOW} for i in range(300, 350))
    seen = {d for i in range(300) for d in depths[i]}
    assert lf.ENOUGH in seen and seen & {5, 6} and not all(set(depths[i]) == {lf.ENOUGH} for i in range(300))
    # A higher limit leaves more runs whole, so nothing has to go up.
    assert set(lf.matched_prefixes(nodes.select("node", "sig", "sketch"), 400).toPandas()["depth"]) == {lf.SHALLOW}


def test_a_family_of_thousands_loses_no_link(spark):
    rng = random.Random(8)
    texts = family(rng, 2500, 90, range(1, 5))
    group, links = exact(texts)
    out = lf.near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), limit=128).collect()
    found = {r["doc_id"]: (r["class_id"], r["n_links"]) for r in out}
    assert [found[i] for i in range(len(texts))] == list(zip(group, links))


def test_a_crowd_under_the_threshold_is_cut_before_it_is_verified(spark, monkeypatch):
    rng = random.Random(4)
    shared = [f"s{i}" for i in range(80)]
    texts = []
    for i in range(300):
        own = [f"o{i}x{j}" for j in range(25)]
        texts += [" ".join(shared + own), " ".join(shared + own[:-2] + ["end", f"e{i}"])]
    monkeypatch.setattr(lf, "TILE", 64)
    tiles = []
    cut = lf.cut_by_rare_shingles
    monkeypatch.setattr(lf, "cut_by_rare_shingles", lambda sets: tiles.append(cut(sets).groupBy("component").count().agg(F.max("count")).first()[0]) or cut(sets))
    group, links = exact(texts)
    out = lf.near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), limit=64).collect()
    found = {r["doc_id"]: (r["class_id"], r["n_links"]) for r in out}
    assert [found[i] for i in range(len(texts))] == list(zip(group, links))
    assert set(links) == {1} and tiles == [2]


def test_kept_rows_hold_their_own_columns_whatever_their_names(spark):
    docs = spark.createDataFrame([(1, "a b c d e f", 7, 8), (2, "a b c d e f", 9, 10)], "doc_id long, text string, rk long, last long")
    assert list(map(tuple, lf.one_of_each_class(docs).collect())) == [(1, "a b c d e f", 7, 8)]
    docs = docs.toDF("doc_id", "text", "_rk", "RK")
    assert list(map(tuple, lf.one_of_each_class(docs).collect())) == [(1, "a b c d e f", 7, 8)]
