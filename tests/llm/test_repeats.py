"""Repeat removal against every window of every text in plain Python."""

import hashlib
import random
from collections import Counter

import duckdb
import numpy as np
import pytest

from exactrank.llm import repeats

SCHEMA = "doc_id long, text string, rk long, spans string"


def brute(rows):
    raws = [(d, (t or "").encode()) for d, t in rows]
    count = Counter(r[i : i + 200] for _, r in raws for i in range(len(r) - 199))
    out = []
    for d, r in raws:
        gone = bytearray(len(r))
        for i in range(len(r) - 199):
            if count[r[i : i + 200]] > 1:
                gone[i : i + 200] = b"\1" * 200
        kept = bytes(b for b, g in zip(r, gone) if not g)
        out.append((d, len(r), sum(gone), sum(g and (i == 0 or not gone[i - 1]) for i, g in enumerate(gone)), hashlib.sha256(kept).hexdigest()))
    return sorted(map(str, out))


def run(spark, rows, crowd=repeats.CROWD, bucket=repeats.BUCKET):
    df = spark.createDataFrame([(d, t, 1, "x") for d, t in rows], SCHEMA).repartition(3)
    return sorted(str(tuple(r)) for r in repeats.repeat_digest(df, crowd, bucket).collect())


def test_the_small_table(spark):
    rows = duckdb.connect().execute("select doc_id, text from '/root/testdata/sf0.001/documents.parquet'").fetchall()
    assert run(spark, rows) == brute(rows)


@pytest.mark.parametrize("crowd", [8192, 4, 1])
def test_edges_of_repeats_at_every_shift(spark, crowd):
    rng = random.Random(7)
    word = lambda n: "".join(rng.choice("abcdefgh é\n") for _ in range(n))
    shared, other = word(500), word(230)
    rows = [(None, None), (1, ""), (2, "short"), (3, "Und " * 200), (4, word(900)), (5, "x" * 199), (6, "y" * 200), (7, "z" * 201)]
    rows += [(20, shared + word(50)), (20, shared + word(50))]
    for i in range(40):
        a, b = sorted((rng.randrange(0, 500), rng.randrange(0, 500)))
        rows.append((100 + i, word(rng.randrange(90)) + shared[a:b] + word(rng.randrange(90)) + other[rng.randrange(40) :] + word(rng.randrange(9))))
    rows += [rows[-1], rows[-1], (500, rows[-1][1])]
    long = word(70000)
    rows += [(600, long), (601, long[:30000] + "!" + long[30001:])]
    assert run(spark, rows, crowd) == brute(rows)
    # Buckets of a few suffixes each: most tokens stand at a boundary.
    assert run(spark, rows, crowd, bucket=64) == brute(rows)


def test_multikey_quicksort_sorts_every_range_by_bytes():
    rng = np.random.default_rng(3)
    data = rng.choice(np.frombuffer(b"ab\xff", np.uint8), 3000)
    at = np.concatenate([rng.integers(0, 2900, 700), rng.integers(0, 40, 300)])
    start, size = np.array([0, 500]), np.array([500, 500])
    order, tied = repeats.multikey_quicksort(1000, 3, lambda i, d: repeats.byte_words(data, at[i] + 8 * d), start, size, np.arange(1000))
    raw = [data[a : a + 24].tobytes() for a in at]
    for own in (range(500), range(500, 1000)):
        assert [raw[i] for i in order[own]] == sorted(raw[i] for i in own)
        often = Counter(raw[i] for i in own)
        assert [bool(t) for t in tied[own]] == [often[raw[i]] > 1 for i in order[own]]
    none = np.zeros(0, np.int64)
    assert repeats.multikey_quicksort(0, 3, None, none, none, none)[0].size == 0


def test_columns_with_the_names_used_inside_stay(spark):
    text = "".join(random.Random(1).choice("abc d") for _ in range(300))
    for names in (["doc_id", "text", "_rk", "_spans"], ["doc_id", "text", "rk", "doc"], ["doc_id", "text", "key of the row", "SPANS of the row"]):
        df = spark.createDataFrame([(1, text + "x", 5, 6), (2, "y" + text, 7, 8)], "doc_id long, text string, a long, b long").toDF(*names)
        out = repeats.remove_repeats(df)
        assert out.columns == names and sorted(map(tuple, out.collect())) == [(1, "x", 5, 6), (2, "y", 7, 8)]


def test_whole_rows_stay_and_texts_shrink(spark):
    rng = random.Random(3)
    same = "".join(rng.choice("abc déf") for _ in range(300))
    df = spark.createDataFrame([(1, same + "É1", "q"), (2, "é2" + same, "r"), (3, None, "s"), (4, same, "t")], "doc_id int, text string, source string")
    assert sorted(map(tuple, repeats.remove_repeats(df).collect())) == [(1, "É1", "q"), (2, "é2", "r"), (3, None, "s"), (4, "", "t")]
    assert repeats.repeat_digest(df.limit(0)).count() == 0
