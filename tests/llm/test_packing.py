"""Packing and chunked encoding: whole encodings, gapless sequences, few of them."""

import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from exactrank.llm import packing
from exactrank.llm.chunks import ByteLevelLibrary, ChunkEncoder, Generations, byte_bpe_encoder, split_before_single_spaces

SF = "/root/testdata/sf0.001"
PATH = public_tokenizers.path("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(PATH)


def test_chunks_join_to_the_whole_encoding(library):
    texts = [r[0] for r in duckdb.connect().execute(f"select text from '{SF}/documents.parquet'").fetchall()]
    texts += ["", " ", "  a  b ", "a\n b", "a \nb", " x", "x ", "it's 5 o'clock\t ok  \n\n  y", "a  b  c", "<|endoftext|> a", "a<|endoftext|>", "x <|endoftext|><|endoftext|>\n y", "<|endoftext", "日本 語 é", "a  \n"]
    encode = byte_bpe_encoder(PATH)
    for t, e in zip(texts, library.encode_batch(texts, add_special_tokens=False)):
        assert list(encode(t)) == e.ids, t


@settings(max_examples=150, deadline=None)
@given(st.lists(st.sampled_from([*" \n\t a'sé1!.<|>", "<|endoftext|>", " word"]), max_size=40).map("".join))
def test_any_spacing_is_encoded_as_by_the_library(library, text):
    assert list(byte_bpe_encoder(PATH)(text)) == library.encode(text, add_special_tokens=False).ids


def test_a_bounded_cache_never_changes_ids(library):
    cache = Generations(2000)
    lib = ByteLevelLibrary(PATH, cache)
    encode = ChunkEncoder(split_before_single_spaces, lib, cache, lib.added, lib.whole)
    for i in range(300):
        text = " ".join(f"w{(i * j) % 37}, é{j % 11}." for j in range(20))
        assert list(encode(text)) == library.encode(text, add_special_tokens=False).ids
    assert len(cache.new) < 100 and len(cache.old) < 100
    encode.forget()
    assert not cache.new and not cache.old


def optimum(lengths, capacity):
    """Fewest sequences, by trying every open one for each piece."""
    lengths = sorted(lengths, reverse=True)
    best = len(lengths)

    def go(i, rooms):
        nonlocal best
        if len(rooms) >= best:
            return
        if i == len(lengths):
            best = len(rooms)
            return
        for k in {r: j for j, r in enumerate(rooms) if r >= lengths[i]}.values():
            go(i + 1, [r - lengths[i] * (j == k) for j, r in enumerate(rooms)])
        go(i + 1, [*rooms, capacity - lengths[i]])

    go(0, [])
    return best


@settings(max_examples=80, deadline=None)
@given(st.lists(st.integers(1, 12), min_size=1, max_size=9))
def test_small_plans_are_near_the_optimum(lengths):
    made = sum(t for _, t in packing.plan_packing(dict(Counter(lengths)), 12))
    assert optimum(lengths, 12) <= made <= optimum(lengths, 12) + 1


def test_exact_complements_are_single_pair_and_triple():
    assert packing.plan_packing({7: 2, 5: 2}, 12) == [((7, 5), 2)]
    assert packing.plan_packing({7: 1, 3: 1, 2: 1}, 12) == [((7, 3, 2), 1)]
    assert packing.plan_packing({6: 1, 3: 1, 2: 1, 1: 1}, 12) == [((6, 3, 2, 1), 1)]
    assert packing.plan_packing({4: 6}, 12) == [((4, 4, 4), 2)]
    # Only one piece of 5 is left for two gaps of 5: the second gap takes the pair.
    assert packing.plan_packing({7: 2, 5: 1, 3: 1, 2: 1}, 12) == [((7, 5), 1), ((7, 3, 2), 1)]


def test_residuals_go_where_least_room_is_left():
    # Nothing is exact: 3 fits beside both, the tighter sequence takes it.
    assert sorted(packing.best_fit({8: 1, 7: 1, 3: 1}, 12)) == [((7,), 1), ((8, 3), 1)]
    assert sorted(packing.best_fit({5: 5}, 12)) == [((5,), 1), ((5, 5), 2)]


@settings(max_examples=150, deadline=None)
@given(st.dictionaries(st.integers(1, 64), st.integers(1, 9), max_size=20))
def test_a_plan_uses_each_piece_once(counts):
    plan = packing.plan_packing(counts, 64)
    used = defaultdict(int)
    for pattern, times in plan:
        assert times > 0 and sum(pattern) <= 64
        for n in pattern:
            used[n] += times
    assert dict(used) == counts
    total = sum(n * c for n, c in counts.items())
    best = -(-total // 64)
    assert best <= sum(t for _, t in plan) <= max(2 * best, 1)


def check_sequences(rows):
    by = defaultdict(list)
    for r in rows:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for own in by.values():
        at = 0
        for offset, length in sorted(own):
            assert offset == at
            at += length
        assert at <= packing.CAPACITY
    return len(by)


def test_packing_of_the_table_and_of_edge_rows(spark, library):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    edges = spark.createDataFrame([(1, None, 5), (1, None, 5), (2, "", 5), (3, "word " * 5000, 5), (None, "x", 5)], "doc_id long, text string, piece int")
    for df in (docs, edges):
        rows = packing.pack_documents(df).collect()
        n = check_sequences(rows)
        assert n <= -(-sum(r["length"] for r in rows) // packing.CAPACITY) * 1.02 + 1
        expected = []
        for d, t in df.select("doc_id", "text").collect():
            ids = np.array([*library.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
            at = 0
            for i, length in enumerate(packing.cut_lengths(len(ids), 1024)):
                expected.append((d, i, at, length, zlib.crc32(ids[at : at + length].tobytes())))
                at += length
        assert sorted(map(str, expected)) == sorted(str((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"])) for r in rows)
    assert packing.pack_documents(spark.createDataFrame([], "doc_id long, text string")).count() == 0
