"""SentencePiece models run by the tokenizers library.

The model's protobuf is parsed from its wire format; normaliser, metaspace marker, scores and
byte fallback are rebuilt from what it says. A unigram model becomes a Unigram of its pieces
and scores; a BPE model becomes a BPE whose merges are all ways to make a piece from two,
ordered by the piece's score. Texts are cut before runs of metaspaces, which no piece
crosses, and each distinct chunk is encoded and decoded once, by the library's model and decoder. Parity with the
sentencepiece library is measured on every text as a whole, ids and decoded text alike: the
reference encodes and decodes each row beside the rebuilt tokenizer.

Defined results: a null text is empty; an empty text has no ids and decodes to ""; texts are
ordinary text throughout (control pieces are never matched); repeated rows are encoded each;
an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from exactrank.llm.chunks import ChunkEncoder, Generations, uncollected
from exactrank.llm.common import documents

METASPACE = "▁"
# Fixed values of the public format: piece types and model types.
NORMAL, UNKNOWN, CONTROL, USER_DEFINED, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
UNIGRAM, BPE = 1, 2
#: One generation of a worker's cache of chunks.
CACHE_BYTES = 160_000_000
#: Chunks that do not decode to themselves and are remembered; with more, texts are decoded whole.
MOST_CHANGED = 10_000


def _fields(data: bytes) -> Iterator[tuple[int, object]]:
    """(number, value) of each field of a protobuf message: ints, 4-byte floats, bytes."""
    at = 0

    def varint() -> int:
        nonlocal at
        value = shift = 0
        while True:
            b = data[at]
            at += 1
            value |= (b & 0x7F) << shift
            if b < 0x80:
                return value
            shift += 7

    while at < len(data):
        tag = varint()
        kind = tag & 7
        if kind == 0:
            yield tag >> 3, varint()
        elif kind == 2:
            n = varint()
            yield tag >> 3, data[at : at + n]
            at += n
        elif kind == 5:
            yield tag >> 3, struct.unpack("<f", data[at : at + 4])[0]
            at += 4
        elif kind == 1:
            yield tag >> 3, data[at : at + 8]
            at += 8
        else:
            raise ValueError(f"wire type {kind}")


@dataclass
class PieceModel:
    pieces: list[tuple[str, float, int]] = field(default_factory=list)
    kind: int = UNIGRAM
    byte_fallback: bool = False
    unk_id: int = 0
    add_prefix: bool = True
    collapse_spaces: bool = True
    escape_spaces: bool = True
    charsmap: bytes = b""

    def unigram_vocabulary(self) -> list[tuple[str, float]]:
        """Pieces that text may match, with scores (control, byte and unknown pieces apart)."""
        return [(p, s) for p, s, t in self.pieces if t in (NORMAL, USER_DEFINED)]


def read_model(path: str) -> PieceModel:
    with open(path, "rb") as f:
        return parse_model(f.read())


def parse_model(data: bytes) -> PieceModel:
    m = PieceModel()
    for number, value in _fields(data):
        if number == 1:
            piece, score, kind = "", 0.0, NORMAL
            for n, v in _fields(value):
                if n == 1:
                    piece = v.decode()
                elif n == 2:
                    score = v
                elif n == 3:
                    kind = v
            m.pieces.append((piece, score, kind))
        elif number == 2:
            for n, v in _fields(value):
                if n == 3:
                    m.kind = v
                elif n == 35:
                    m.byte_fallback = bool(v)
                elif n == 40:
                    m.unk_id = v
        elif number == 3:
            for n, v in _fields(value):
                if n == 2:
                    m.charsmap = v
                elif n == 3:
                    m.add_prefix = bool(v)
                elif n == 4:
                    m.collapse_spaces = bool(v)
                elif n == 5:
                    m.escape_spaces = bool(v)
    return m


def _merges(model: PieceModel) -> list[tuple[str, str]]:
    rank = {p: i for i, (p, _, t) in enumerate(model.pieces) if t in (NORMAL, USER_DEFINED, UNUSED)}
    found = []
    for p, i in rank.items():
        ways = [(rank[p[:k]], rank[p[k:]], p[:k], p[k:]) for k in range(1, len(p)) if p[:k] in rank and p[k:] in rank]
        found += [(-model.pieces[i][1], i, *w) for w in ways]
    return [(a, b) for *_, a, b in sorted(found)]


def rebuild(model: PieceModel):
    """A tokenizers-library Tokenizer that encodes and decodes as the model does."""
    from tokenizers import Regex, Tokenizer, decoders, models, normalizers

    if model.kind == BPE:
        vocab = {p: i for i, (p, _, _) in enumerate(model.pieces)}
        core = models.BPE(vocab, _merges(model), unk_token=model.pieces[model.unk_id][0], fuse_unk=True, byte_fallback=model.byte_fallback)
    elif model.kind == UNIGRAM:
        core = models.Unigram([(p, s) for p, s, _ in model.pieces], model.unk_id, model.byte_fallback)
    else:
        raise ValueError("unigram and BPE models only")
    out = Tokenizer(core)
    steps = []
    if model.charsmap:
        steps.append(normalizers.Precompiled(model.charsmap))
    if model.collapse_spaces:
        steps += [normalizers.Strip(), normalizers.Replace(Regex(" {2,}"), " ")]
    if model.add_prefix:
        steps.append(normalizers.Prepend(METASPACE if model.escape_spaces else " "))
    if model.escape_spaces:
        steps.append(normalizers.Replace(" ", METASPACE))
    out.normalizer = normalizers.Sequence(steps)
    # Only turns markers into spaces; dropping the first one is a step of its own below.
    parts = [decoders.Metaspace(METASPACE, prepend_scheme="never")]
    if model.byte_fallback:
        parts.append(decoders.ByteFallback())
    parts.append(decoders.Fuse())
    if model.add_prefix:
        parts.append(decoders.Strip(" ", 1, 0))
    out.decoder = decoders.Sequence(parts)
    return out


_CHUNK = re.compile(f"{METASPACE}+[^{METASPACE}]*|[^{METASPACE}]+")


class PieceCodec:
    """Encoding of whole texts in cached chunks, and decoding."""

    def __init__(self, model: PieceModel):
        self.model = model
        self.tokenizer = rebuild(model)
        self.normalizer, self._core = self.tokenizer.normalizer, self.tokenizer.model
        self._packed = [i.to_bytes(4, "little") for i in range(len(model.pieces))]
        # The cut is exact only if no piece has a metaspace after another character.
        whole = any(METASPACE in p.lstrip(METASPACE) for p, _, t in model.pieces if t == NORMAL)
        self.simple = not whole and not model.charsmap and not model.collapse_spaces and model.add_prefix and model.escape_spaces
        # Such chunks begin with a marker's piece, so that nothing decodes across their bounds.
        self.by_chunks = self.simple and any(p == METASPACE and t == NORMAL for p, _, t in model.pieces)
        self.changed: set[str] = set()
        self.encode_text = ChunkEncoder((lambda t: [t] if t else []) if whole else self._chunks, self._encode, Generations(CACHE_BYTES))

    def _chunks(self, text: str) -> list[str]:
        if not text:
            return []
        if self.simple:
            # Chunks go without their first marker, so that they are bare words.
            words = text.split(" ")
            if "" not in words and METASPACE not in text:
                return words
            return [c[1:] for c in _CHUNK.findall(METASPACE + text.replace(" ", METASPACE))]
        return _CHUNK.findall(self.normalizer.normalize_str(text))

    def _encode(self, chunks: list[str]) -> list[bytes]:
        # Chunks are normalised already, so the bare model takes them; a batch of the library's
        # whole tokenizer costs two to six times the CPU on such short strings.
        merge, packed, marker = self._core.tokenize, self._packed, METASPACE if self.simple else ""
        if not self.by_chunks:
            return [b"".join([packed[t.id] for t in merge(marker + c)]) for c in chunks]
        out, decode = [], self.tokenizer.decode
        for c in chunks:
            ids = [t.id for t in merge(marker + c)]
            if len(self.changed) <= MOST_CHANGED and decode(ids, skip_special_tokens=False) != c:
                self.changed.add(c)
            out.append(b"".join([packed[i] for i in ids]))
        return out

    def decode_encoded(self, text: str, ids: list[int]) -> str:
        """``decode(ids)`` for the ids that ``encode_text(text)`` has just given. Chunks were decoded
        when they were encoded; where each gave itself, joined they are the text."""
        if self.by_chunks and len(self.changed) <= MOST_CHANGED and text and METASPACE not in text:
            words = text.split(" ") if self.changed or "  " in text or text[0] == " " or text[-1] == " " else None
            if words is None or "" not in words and self.changed.isdisjoint(words):
                return text
        return self.decode(ids)

    def forget(self) -> None:
        self.changed.clear()
        self.encode_text.forget()

    def decode(self, ids: list[int]) -> str:
        return self.tokenizer.decode(ids, skip_special_tokens=False)


_codecs: dict[str, PieceCodec] = {}


def codec(path: str) -> PieceCodec:
    if path not in _codecs:
        _codecs[path] = PieceCodec(read_model(path))
    return _codecs[path]


def encode_documents(docs: DataFrame, model: str, with_ids: bool = False) -> DataFrame:
    """doc_id, n_ids, ids_crc32 (little-endian unsigned 32-bit), decoded_crc32 (of the decoded
    text's UTF-8), round_trip (decoded text is the text), parity (the reference library gives the
    same ids and decodes them to the same text) for each text of ``docs(doc_id, text)``; the ids
    too if asked for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from sentencepiece import SentencePieceProcessor

        own, reference = codec(model), SentencePieceProcessor(model_file=model)
        with uncollected():
            for batch in batches:
                rows = []
                for doc, text in zip(batch["doc_id"].to_pylist(), batch["text"].to_pylist()):
                    text = text or ""
                    ids = own.encode_text(text)
                    listed = ids.tolist()
                    decoded = own.decode_encoded(text, listed)
                    parity = reference.encode(text) == listed and reference.decode(listed) == decoded
                    packed = ids.tobytes()
                    rows.append((doc, len(ids), zlib.crc32(packed), zlib.crc32(decoded.encode()), decoded == text, parity, packed))
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.bool_(), pa.binary()]
                names = ["doc_id", "n_ids", "ids_crc32", "decoded_crc32", "round_trip", "parity", "ids"]
                keep = 7 if with_ids else 6
                columns = list(zip(*rows)) or [()] * 7
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in list(zip(columns, kinds))[:keep]], names[:keep])
        own.forget()

    schema = "doc_id long, n_ids long, ids_crc32 long, decoded_crc32 long, round_trip boolean, parity boolean"
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, schema + (", ids binary" if with_ids else ""))


def decode_documents(encoded: DataFrame, model: str) -> DataFrame:
    """doc_id, text for ``encoded(doc_id, ids)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(model)
        for batch in batches:
            texts = [own.decode(np.frombuffer(ids or b"", "<u4").tolist()) for ids in batch["ids"].to_pylist()]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def op8_sentence_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return encode_documents(documents(spark, sf_dir, "doc_id", "text"), public_tokenizers.path("piece_bpe_32k.model"))
