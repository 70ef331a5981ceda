"""Each stage of the pipeline against plain Python on what the stage before it kept."""

import sys
from collections import Counter
from pathlib import Path

sys.path.insert(0, str(Path(__file__).parents[2]))
import corpus_pipeline as cp  # noqa: E402

from exactrank.llm import quality  # noqa: E402

SF = "/root/testdata/sf0.001"


def test_stages_in_turn(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    verdict = quality.train(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    good = {r["doc_id"] for r in quality.assess_quality(docs, verdict).where("kept").collect()}
    kept = []
    for i, (name, stage) in enumerate(cp.STAGES):
        out = stage(spark, docs, SF)
        if i < 3:
            assert out.columns == docs.columns
            out.write.parquet(str(tmp_path / name))
            docs = spark.read.parquet(str(tmp_path / name))
            kept.append({r["doc_id"]: r["text"] for r in docs.collect()})
        else:
            last = out.collect()
    assert set(kept[0]) == good

    def parts(t):
        w = t.split()
        return {tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))}

    sets = {d: parts(t) for d, t in kept[0].items()}
    group = {d: d for d in sets}
    near = {d: [e for e in sets if 10 * len(sets[d] & sets[e]) >= 8 * len(sets[d] | sets[e])] for d in sets}
    for _ in range(20):
        group = {d: min(group[e] for e in near[d]) for d in sets}
    assert set(kept[1]) == set(group.values())
    count = Counter()
    raws = {d: t.encode() for d, t in kept[1].items()}
    for r in raws.values():
        count.update(r[j : j + 200] for j in range(len(r) - 199))
    for d, r in raws.items():
        gone = bytearray(len(r))
        for j in range(len(r) - 199):
            if count[r[j : j + 200]] > 1:
                gone[j : j + 200] = b"\1" * 200
        assert kept[2][d] == bytes(b for b, g in zip(r, gone) if not g).decode("utf-8", "ignore")
    assert {r["doc_id"] for r in last} == set(kept[2])
    assert cp.run(spark, SF).count() == len(last)


def test_edge_rows_and_clashing_columns_go_through(spark, tmp_path):
    good = [r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").orderBy("doc_id").limit(12).collect()]
    rows = [(i, t, 5, "a", b"x", 1) for i, t in enumerate(good)] + [(0, good[0], 5, "a", b"x", 1), (None, good[1], 5, None, None, None), (50, None, None, None, None, None), (51, "", 0, "b", b"", 2), (52, " \n", 2, "b", b"", 2)]
    schema = "doc_id long, text string, n_chars long, _rk string, _spans binary, rk int"
    spark.createDataFrame(rows, schema).write.parquet(str(tmp_path / "documents.parquet"))
    # No labels: the base rules decide alone.
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    for name, stage in cp.STAGES[:3]:
        out = stage(spark, docs, str(tmp_path))
        assert out.schema == docs.schema, name
        out.write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
    kept = {(r["doc_id"], r["_rk"]) for r in docs.collect()}
    # Copies are one, and texts without ten words are gone.
    assert len(kept) == docs.count() and {d for d, _ in kept} <= set(range(12)) and (1, "a") in kept
    assert {r["doc_id"] for r in cp.run(spark, str(tmp_path)).collect()} == {d for d, _ in kept}
    empty = tmp_path / "empty"
    spark.createDataFrame([], schema).write.parquet(str(empty / "documents.parquet"))
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(str(empty / "labels.parquet"))
    assert cp.run(spark, str(empty)).count() == 0


def test_probability_is_that_of_a_plain_scorer():
    """Features word by word and character by character, without the kernels' windows."""
    import numpy as np
    import pyarrow as pa

    from exactrank.llm.textkernel import SpanHash, mix, ngram_hash

    rng = np.random.default_rng(3)
    verdict = quality.Verdict(rng.normal(size=1 << quality.BITS).astype(np.float32), 0.1, 2.0, -0.3)
    texts = ["one two  three\n two one", "é日本 x 😀 word", "a", "", "ab\tcd"]

    def slot(h):
        return int(mix(np.array([h], np.uint64))[0] >> np.uint64(64 - quality.BITS))

    def word(w):
        raw = np.frombuffer(w.encode(), np.uint8)
        return SpanHash(raw)(np.array([0]), np.array([len(raw)]))

    def mean(slots):
        return sum(float(verdict.weights[s]) for s in slots) / len(slots) if slots else 0.0

    def gram(points, seed):
        h = seed
        for p in points:
            h = (h * 0x9E3779B97F4A7C15 + p) % 2**64
        return slot(h)

    for text, found in zip(texts, quality.assess(pa.array(texts), verdict)["probability"]):
        hashes = [word(w) for w in text.split()]
        score = mean([slot(h[0]) for h in hashes])
        score += mean([slot((int(ngram_hash(np.concatenate([a, b]), 2)[0]) + 0x9216D5D9) % 2**64) for a, b in zip(hashes, hashes[1:])])
        for n, seed in ((3, 0x51ED270B), (4, 0x2545F491)):
            score += mean([gram([ord(c) for c in text[i : i + n]], seed) for i in range(len(text) - n + 1)])
        assert abs(found - 1 / (1 + np.exp(-(2.0 * (score + 0.1) - 0.3)))) < 1e-6, text
