"""Sharding and license scans against their SQL, plain Python and edge rows."""

import re
import zlib
from collections import defaultdict

import duckdb
import pytest
from pyspark.sql import functions as F

from exactrank.llm import licenses, registry, sharding

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["op3_rendezvous_shards", "op4_lsh_forest_join", "op7_license_scan"])
def test_queries_equal_their_sql(spark, name):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    cursor = con.execute(registry.oracle_sql()[name])
    names = [d[0] for d in cursor.description]
    out = registry.queries()[name](spark, SF)
    assert sorted(names) == sorted(out.columns)
    assert sorted(str([r[c] for c in names]) for r in out.collect()) == sorted(str(list(r)) for r in cursor.fetchall())


def test_sharding_of_edge_rows(spark, tmp_path):
    rows = [(1, "a", "x"), (1, "a", "x"), (2, None, "x"), (None, "é", "x"), (None, None, "x")] + [(i, "t" * (i % 9), "y") for i in range(10, 400)]
    spark.createDataFrame(rows, "doc_id long, text string, shard string").write.parquet(str(tmp_path / "documents.parquet"))
    out = sharding.op3_rendezvous_shards(spark, str(tmp_path)).collect()
    assert len(out) == len(rows)
    slots = defaultdict(list)
    for r in out:
        slots[r["shard"]].append(r["slot"])
        assert 0 <= r["shard"] < 16 and r["grown_shard"] in (r["shard"], 16)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    want = sorted((len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for _, t, _ in rows)
    assert sorted((r["size"], r["text_crc32"]) for r in out) == want
    assert len({r["shard"] for r in out if r["doc_id"] == 1}) == 1


def test_weights_and_few_moves(spark):
    df = spark.range(20000)
    w = [1.0, 2.0, 0.0, 1.0]
    before = sharding.assign_shards(df, "id", w)
    counts = {r["shard"]: r["count"] for r in before.groupBy("shard").count().collect()}
    assert set(counts) == {0, 1, 3} and abs(counts[1] - 10000) < 400 and abs(counts[0] - 5000) < 400
    both = sharding.assign_shards(before, "id", [*w, 1.0], "grown")
    assert both.where("grown <> shard AND grown <> 4").count() == 0
    assert abs(both.where("grown = 4").count() - 4000) < 400
    with pytest.raises(ValueError):
        sharding.rendezvous(F.col("id"), [0.0])


def test_license_places_and_alignments(spark):
    texts = [
        None, "", "Apache", "The APACHE-License, v2; apache\nlicense!", "cc by cc by", "GNU General Public License", "gnu general public licence",
        "İ mit license K mit licenseK", "word " * 20000 + "mit license",
        # A word lost and one put in: the neighbouring diagonals together hold enough pairs.
        "permission is hereby granted free of any charge to any person obtaining a copy of this software",
        "permission is granted", "licensed under CC BY-NC 4.0.",
    ]
    rows = [(i, t, "x") for i, t in enumerate(texts)] + [(3, texts[3], "x"), (None, "mit license", "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, label string")
    out = {r["doc_id"]: r for r in licenses.scan_licenses(df).collect()}
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    for i, t in enumerate(texts):
        words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(low))
        at = sorted((p, label) for phrase, label in licenses.PHRASES for p in range(len(words)) if words[p : p + len(phrase.split())] == phrase.split())
        r = out[i]
        assert (r["n_words"], r["n_base"]) == (len(words), len(at)), t
        assert (r["first_word"], r["last_word"]) == ((at[0][0], at[-1][0]) if at else (None, None))
        assert r["base_labels"] == ",".join(sorted({x for _, x in at})) and set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(","))
        assert 0 <= r["score"] <= 1
    assert out[9]["labels"] == "mit" and out[10]["labels"] == "" and out[11]["labels"] == "cc-by,cc-by-nc" and out[None]["labels"] == "mit"
    assert licenses.scan_licenses(df).count() == len(rows) and licenses.scan_licenses(df.limit(0)).count() == 0


def test_any_part_of_a_licence_is_found_and_its_span_verified(spark):
    parts = dict(enumerate(licenses.TEMPLATES))
    warranty = next(t for t, label in licenses.TEMPLATES if label == "mit" and t.startswith("the software is provided"))
    section = max((t for t, label in licenses.TEMPLATES if label == "apache-2.0"), key=len)
    words = section.split()
    changed = " ".join(w if i % 40 else "x" for i, w in enumerate(words))
    rows = [(i, "before it " + t.upper() + " after it") for i, (t, _) in parts.items()]
    rows += [(1000, warranty), (1001, changed), (1002, " ".join(words[: len(words) // 3])), (1003, " ".join(reversed(words))), (1004, " ".join(words[len(words) // 2 :] + words[: len(words) // 2]))]
    # Six words put in move the rest to a neighbouring diagonal; forty do not belong to the alignment.
    rows += [(1005, " ".join([*words[:90], *"one two three four five six".split(), *words[90:]]))]
    out = {r["doc_id"]: r for r in licenses.scan_licenses(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i, (t, label) in parts.items():
        assert label in out[i]["labels"].split(","), t
        # An alignment covers the part and nothing before or behind it.
        assert any(x["label"] == label and (x["start"], x["end"]) == (2, 1 + len(t.split())) and x["share"] == 1 for x in out[i]["spans"])
        assert out[i]["score"] == 1
    assert "mit" in out[1000]["labels"].split(",") and "apache-2.0" in out[1001]["labels"].split(",") and out[1001]["score"] < 1
    assert not {"apache-2.0"} & set(out[1002]["labels"].split(",")) and 0.2 < out[1002]["score"] < 0.45
    assert out[1003]["labels"] == "" and "apache-2.0" in out[1005]["labels"].split(",")
    assert out[1004]["score"] < 0.6


def test_slots_keep_columns_of_any_name(spark):
    df = spark.createDataFrame([(i, 0, i, i, i, i) for i in range(9)], "id long, shard int, _group long, _nth long, _s long, `slot group` long")
    out = sharding.with_slots(df, "shard", "id", ["id"])
    assert out.columns == [*df.columns, "slot"]
    rows = out.collect()
    assert sorted(r["slot"] for r in rows) == list(range(9)) and all(r["_group"] == r["_nth"] == r["_s"] == r["slot group"] == r["id"] for r in rows)
