"""Piece models against the sentencepiece and tokenizers libraries."""

import duckdb
import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer, models

from exactrank.llm import sentence_pieces as sp
from exactrank.llm import unigram_counts as uc

SF = "/root/testdata/sf0.001"
MODEL = public_tokenizers.path("piece_bpe_32k.model")
ODD = ["", " ", "a", " a  b ", "line\nline\t x", "日本 \U0001f600 é", "a" * 3000, "  ", "x ", "<s> </s> <unk> <0x0A>", "▁a"]


@pytest.fixture(scope="module")
def texts():
    return [r[0] for r in duckdb.connect().execute(f"select text from '{SF}/documents.parquet'").fetchall()]


def test_encoding_and_decoding_equal_the_reference_library(texts):
    from sentencepiece import SentencePieceProcessor

    ref, own = SentencePieceProcessor(model_file=MODEL), sp.codec(MODEL)
    for t in [*texts, *ODD]:
        ids = own.encode_text(t)
        assert ref.encode(t) == ids.tolist(), t[:50]
        assert ref.decode(ids.tolist()) == own.decode(ids.tolist()), t[:50]
    for t in texts:
        ids = own.encode_text(t)
        assert own.decode(ids.tolist()) == t


def test_query_and_edge_rows(spark, texts):
    df = spark.createDataFrame([(i * 50, t, 0) for i, t in enumerate([None, *ODD[:9]])], "doc_id long, text string, ids int")
    out = sp.encode_documents(df, MODEL, with_ids=True)
    rows = {r["doc_id"]: r for r in out.collect()}
    assert all(r["parity"] for r in rows.values()) and rows[0]["n_ids"] == 0
    assert {r["doc_id"]: r["text"] for r in sp.decode_documents(out, MODEL).collect()} == {i * 50: t or "" for i, t in enumerate([None, *ODD[:9]])}
    assert sp.encode_documents(df.limit(0), MODEL).count() == 0
    assert uc.count_tokens(df.limit(0), MODEL).count() == 0
    counts = {r["doc_id"]: r["n_tokens"] for r in uc.count_tokens(df, MODEL).collect()}
    assert counts[0] == 0 and counts[100] == 1 or counts[100] > 0


def test_every_row_is_compared_with_the_reference(spark, texts, tmp_path):
    schema = "doc_id long, text string"
    rows = [(1, texts[0]), (51, None), (None, texts[1]), (50, "é"), (-3, ODD[4])]
    assert [r["parity"] for r in sp.encode_documents(spark.createDataFrame(rows, schema), MODEL).collect()] == [True] * 5
    # The reference takes a user-defined piece whole, the rebuilt tokenizer cannot: rows with it are flagged.
    piece = b"qzjx"
    message = bytes([0x0A, len(piece)]) + piece + bytes([0x15]) + bytes(4) + bytes([0x18, sp.USER_DEFINED])
    with open(MODEL, "rb") as f:
        (tmp_path / "more.model").write_bytes(f.read() + bytes([0x0A, len(message)]) + message)
    rows = [(1, "some qzjx here"), (2, "some words"), (None, "qzjx")]
    out = sp.encode_documents(spark.createDataFrame(rows, schema), str(tmp_path / "more.model")).collect()
    assert {r["doc_id"]: r["parity"] for r in out} == {1: False, 2: True, None: False}


def unigram(pieces, byte_fallback):
    vocab = [("<unk>", 0.0)] + ([(f"<0x{b:02X}>", 0.0) for b in range(256)] if byte_fallback else []) + list(pieces)
    return Tokenizer(models.Unigram(vocab, 0, byte_fallback))


def test_counts_equal_the_library(texts):
    m = sp.read_model(MODEL)
    counter = uc.WordCounter(m.unigram_vocabulary(), True)
    # The library's unknown score hangs on its lowest score: give it the same vocabulary.
    lib = unigram(m.unigram_vocabulary(), True)
    some = [t for t in texts if len(t) < 6000] + [t for t in ODD if "▁" not in t]
    for t, c in zip(some, counter(some)):
        marked = ("▁" + t.replace(" ", "▁")) if t else ""
        assert c == len(lib.encode(marked).ids), t[:60]


@settings(max_examples=200, deadline=None)
@given(st.dictionaries(st.text("ab▁é", min_size=1, max_size=4).filter(lambda p: "▁" not in p.lstrip("▁")), st.sampled_from([-1.0, -2.0, -3.0, -4.5]), min_size=1, max_size=12), st.text("ab éc", max_size=14))
def test_ties_are_broken_as_the_library_does(pieces, text):
    pieces = list(pieces.items())
    # Its unknown score is its lowest score less 10, so <unk> gets the highest.
    lib = Tokenizer(models.Unigram([("<unk>", 0.0), *pieces], 0, False))
    marked = "▁" + text.replace(" ", "▁") if text else ""
    if "▁" not in dict(pieces):
        return  # unknown runs could then cross words
    assert uc.WordCounter(pieces, False)([text])[0] == len(lib.encode(marked).ids)


def test_texts_decode_by_their_chunks(monkeypatch):
    own = sp.PieceCodec(sp.read_model(public_tokenizers.path("piece_bpe_32k.model")))
    assert own.by_chunks
    texts = ["", " ", "a b", " a  b ", "a▁b c", "x\ny z\t", "<s> </s> <unk> <0x41>", "naïve 漢字 🙂 é", "\x00 \x7f", "tail ", "🙂 🙂", "a b" * 50]
    whole, asked = own.decode, []
    monkeypatch.setattr(own, "decode", lambda ids: asked.append(1) or whole(ids))
    for most in (sp.MOST_CHANGED, -1):
        monkeypatch.setattr(sp, "MOST_CHANGED", most)
        for t in [*texts, *texts]:
            ids = own.encode_text(t).tolist()
            assert own.decode_encoded(t, ids) == whole(ids)
        if most > 0:
            assert len(asked) < len(texts)
    own.changed.add("b")
    monkeypatch.setattr(sp, "MOST_CHANGED", 5)
    asked.clear()
    assert own.decode_encoded("a b", own.encode_text("a b").tolist()) == "a b" and asked
