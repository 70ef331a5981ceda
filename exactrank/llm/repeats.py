"""Removal of repeated passages by sorting sampled suffixes.

A byte goes if it is covered by a string of ``LENGTH`` bytes that also starts anywhere else.
Of all suffixes only those are sorted that can matter. Every window of LENGTH bytes has one
leading token: the 40-byte string of least hash within it. Equal windows have equal leading
tokens at equal places, so suffixes that begin at a leading token stand for all windows around.

1. Suffixes are range-partitioned on their leading tokens, byte order, with the splitters that
   Spark's range exchange samples (repeats within a task are settled first, so a passage that
   everyone shares arrives once from each task). Each bucket is sorted by multikey quicksort,
   eight bytes a key. A token that stands once is done: nothing near it repeats. If all that
   its windows cover is the same elsewhere, all of these windows repeat.
2. What is left are the edges of repeats: tokens that recur with different surroundings, and the
   first and last token of each bucket, which may go on across the boundary. Their covers are
   fetched, range-partitioned on the token with splitters from a bounded sample, so that both
   sides of a boundary meet, and each bucket's windows are sorted by multikey quicksort on
   their bytes, going on only with windows that are still tied.
3. A token with more than ``CROWD`` different surroundings is not one task's work: its windows
   are dealt out one by one, by the hash of the whole window.

Covers in step 1 and windows in step 3 are compared by 64-bit hashes beside the token's. Rows are
told apart by doc_id and a hash of id and text. Defined results: a null text is empty; texts under
LENGTH bytes stay whole; repeated rows are places of their own, so both copies go; an empty
table gives no rows; ``remove_repeats`` keeps every column and every row, a text of which
nothing stays becomes empty.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from exactrank.llm.common import documents, materialise, own_name, shuffle_width
from exactrank.llm.textkernel import SpanHash, mix, pieces, squeeze, swell, text_buffer

LENGTH = 200
TOKEN = 40
#: Different surroundings of one token that a single task compares.
CROWD = 4096
#: Suffixes in a bucket of either sort, about.
BUCKET = 200_000
EDGE_BUCKET = 50_000
#: Ranges of tokens that the driver holds splitters for at most, and keys sampled for each. Beyond
#: that a range is divided by the token's hash.
RANGES, SAMPLED = 4096, 20
#: Suffixes that a task holds before it settles repeats among them.
HOLD = 300_000
_PLACE_BITS = np.uint64(34)

# Rows are columns of integers. A suffix: the leading token's bytes as five ordered numbers, a
# hash of all that its windows cover, its row (key and id), and its first window, number of
# windows less 1, token's place from there, "seen twice". A span (settled): anything, end,
# row, start.
_WORDS = TOKEN // 8
_COLUMNS = [*(f"w{i}" for i in range(_WORDS)), "body", "rk", "doc", "meta"]
_ROW = ", ".join(f"{c} long" for c in _COLUMNS)
BODY, RK, DOC, META = range(_WORDS, _WORDS + 4)
_SPAN = 1
_SIGN = np.uint64(1 << 63)


def _pack(first, more, place, twice):
    return (first << 18) | (more << 10) | (place << 2) | (twice << 1)


def _unpack(meta: np.ndarray):
    return meta >> 18, (meta >> 10) & 255, (meta >> 2) & 255, (meta >> 1) & 1


def _batch(rows: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(x)) for x in rows], _COLUMNS)


def _rows(batch: pa.RecordBatch) -> np.ndarray:
    return np.stack([batch[c].to_numpy() for c in _COLUMNS])


def token_key(rows: np.ndarray) -> np.ndarray:
    """64 bits for the leading token."""
    key = np.zeros(rows.shape[1], np.uint64)
    for w in rows[:_WORDS]:
        key = mix(key * np.uint64(0xD6E8FEB86659FD93) + w.view(np.uint64))
    return key


def byte_words(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The eight bytes from each position on, as signed numbers in byte order."""
    out = np.zeros(len(at), np.uint64)
    for i in range(8):
        out = (out << np.uint64(8)) | data[at + i].astype(np.uint64)
    return (out ^ _SIGN).view(np.int64)


def multikey_quicksort(n: int, depth: int, word: Callable[[np.ndarray, int], np.ndarray], start: np.ndarray, size: np.ndarray, order: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sort ``order`` (element numbers) within ranges (start, size) by keys of ``depth`` words;
    ``word(elements, d)`` gives the d-th words. Returns the order and, by position, whether an
    element ties with another of its range in every word.

    All open ranges are split at once by their own pivots into less, equal and greater; equal
    parts go on with the next word, and a part of one element is done.
    """
    order, tied = order.copy(), np.zeros(n, bool)
    level = np.zeros(len(start), np.int64)
    while True:
        done = level == depth
        for s, z in zip(start[done & (size > 1)].tolist(), size[done & (size > 1)].tolist()):
            tied[s : s + z] = True
        live = ~done & (size > 1)
        start, size, level = start[live], size[live], level[live]
        if not len(start):
            return order, tied
        own = np.repeat(np.arange(len(start)), size)
        at = np.arange(len(own)) + np.repeat(start - (np.cumsum(size) - size), size)
        elements = order[at]
        w = np.empty(len(own), np.int64)
        for d in np.unique(level):
            here = level[own] == d if len(start) > 1 else slice(None)
            w[here] = word(elements[here], int(d))
        edge = np.cumsum(size) - size
        pivot = np.sort(np.stack([w[edge], w[edge + size // 2], w[edge + size - 1]]), 0)[1][own]
        part = own * 3 + (w > pivot) - (w < pivot) + 1
        order[at] = elements[np.argsort(part, kind="stable")]
        count = np.bincount(part, minlength=3 * len(start))
        begin = np.cumsum(count) - count
        begin += np.repeat(start - edge, 3)
        start, size, level = begin, count, np.repeat(level, 3)
        level[1::3] += 1


def leading_tokens(data: np.ndarray, offs: np.ndarray):
    """(row, first window, windows, token's position) of every run of windows with one leading
    token, positions in the buffer."""
    none = np.zeros(0, np.int64)
    n = len(data) - LENGTH + 1
    if n <= 0 or np.diff(offs).max(initial=0) < LENGTH:
        return none, none, none, none, None
    spans = SpanHash(data)
    h = spans.sliding(TOKEN)
    low = ((h >> _PLACE_BITS) << _PLACE_BITS) | np.arange(len(h), dtype=np.uint64)
    width, have = LENGTH - TOKEN + 1, 1
    while 2 * have <= width:
        low = np.minimum(low[:-have], low[have:])
        have *= 2
    if have < width:
        low = np.minimum(low[: len(low) - (width - have)], low[width - have :])
    at = (low & np.uint64((1 << 34) - 1)).astype(np.int64)[:n]
    edge = np.zeros(n + 1, np.int64)
    begin, end = offs[:-1], np.maximum(offs[1:] - LENGTH + 1, offs[:-1])
    real = end > begin
    edge[begin[real]] += 1
    np.add.at(edge, end[real], -1)
    inside = np.cumsum(edge[:n]) > 0
    change = inside.copy()
    change[1:] &= (at[1:] != at[:-1]) | ~inside[:-1]
    stop = inside.copy()
    stop[:-1] &= (at[1:] != at[:-1]) | ~inside[1:]
    first, last = np.flatnonzero(change), np.flatnonzero(stop)
    return np.searchsorted(offs, first, "right") - 1, first, last - first + 1, at[first], spans


def _settle(rows: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Spans of suffixes whose whole cover repeats among these, and one row for each cover."""
    key = token_key(rows)
    order = np.lexsort((rows[RK], rows[BODY], key))
    rows, key = rows[:, order], key[order]
    fresh = np.ones(len(key), bool)
    fresh[1:] = (key[1:] != key[:-1]) | (rows[BODY][1:] != rows[BODY][:-1])
    size = np.diff(np.append(np.flatnonzero(fresh), len(key)))
    many = np.repeat(size > 1, size)
    yield _span_batch(rows[:, many])
    rows[META] |= many.astype(np.int64) << 1
    yield _batch(rows[:, fresh])


def _span_batch(rows: np.ndarray, start: np.ndarray | None = None, end: np.ndarray | None = None) -> pa.RecordBatch:
    """Settled spans (of whole covers, if not told), those of a document that touch made one,
    dealt by document."""
    rk, doc = rows[RK], rows[DOC]
    if start is None:
        start, more, _, _ = _unpack(rows[META])
        end = start + more + LENGTH
    order = np.lexsort((start, doc, rk))
    rk, doc, start, end = rk[order], doc[order], start[order], end[order]
    if len(rk):
        fresh = np.ones(len(rk), bool)
        # Ends may not rise with starts, so compare with the greatest end so far of the document.
        row = np.cumsum(np.append(True, (rk[1:] != rk[:-1]) | (doc[1:] != doc[:-1])))
        reach = np.maximum.accumulate(end + (row << 40)) - (row << 40)
        fresh[1:] = (row[1:] != row[:-1]) | (start[1:] > reach[:-1])
        end = np.maximum.reduceat(end, np.flatnonzero(fresh))
        rk, doc, start = rk[fresh], doc[fresh], start[fresh]
    out = np.zeros((len(_COLUMNS), len(rk)), np.int64)
    out[0] = mix(rk.view(np.uint64) + start.astype(np.uint64)).view(np.int64)
    out[BODY], out[RK], out[DOC], out[META] = end, rk, doc, (start << 18) | _SPAN
    return _batch(out)


def _suffix_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: list[np.ndarray] = []

    def flush():
        if held:
            yield from _settle(np.concatenate(held, 1))
            held.clear()

    for batch in batches:
        rks, docs = batch["rk"].to_numpy(), batch["doc"].to_numpy()
        data, offs = text_buffer(batch["text"])
        for lo, _, part, cut in pieces(data, offs):
            row, first, windows, at, spans = leading_tokens(part, cut)
            if len(row):
                place = at - first
                rows = np.empty((len(_COLUMNS), len(row)), np.int64)
                for i in range(_WORDS):
                    rows[i] = byte_words(part, at + 8 * i)
                rows[BODY] = mix(spans(first, first + windows + LENGTH - 1) + place.astype(np.uint64) + (windows.astype(np.uint64) << np.uint64(32))).view(np.int64)
                rows[RK], rows[DOC], rows[META] = rks[lo + row], docs[lo + row], _pack(first - cut[row], windows - 1, place, 0)
                held.append(rows)
        if sum(h.shape[1] for h in held) > HOLD:
            yield from flush()
    yield from flush()


def _range_bucket(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One range of leading tokens: sorted, its settled spans, and one suffix of each cover of the
    tokens that are not settled."""
    parts = [_rows(b) for b in batches if b.num_rows]
    if parts:
        rows = np.concatenate(parts, 1)
        del parts
        settled = (rows[META] & _SPAN) > 0
        if settled.any():
            yield _batch(rows[:, settled])
            rows = rows[:, ~settled]
        yield from _compared(rows)


def _compared(rows: np.ndarray) -> Iterator[pa.RecordBatch]:
    n = rows.shape[1]
    if not n:
        return
    order, _ = multikey_quicksort(n, _WORDS + 1, lambda i, d: rows[d, i], np.zeros(1, np.int64), np.full(1, n), np.arange(n))
    rows = rows[:, order]
    token = np.append(True, (rows[:_WORDS, 1:] != rows[:_WORDS, :-1]).any(0))
    cover = token.copy()
    cover[1:] |= rows[BODY][1:] != rows[BODY][:-1]
    heads = np.flatnonzero(cover)
    size = np.diff(np.append(heads, n))
    twice = (size > 1) | (np.bitwise_or.reduceat((rows[META] >> 1) & 1, heads) > 0)
    yield _span_batch(rows[:, np.repeat(twice, size)])
    # Covers of one token stand together: more than one, or one at the bucket's edge, stay open.
    number = np.cumsum(token[heads]) - 1
    open_ = np.bincount(number)[number] > 1
    open_ |= (number == 0) | (number == number[-1])
    left = rows[:, heads[open_]]
    left[META] &= ~np.int64(3)
    left[BODY] = token_key(left).view(np.int64)
    yield _batch(left)


def _covers(batch: pa.RecordBatch):
    """Token key, crowdedness, row, meta and covered bytes of the suffixes wanted from each text."""
    numbers, covers = [], []
    for rk, doc, text, wanted in zip(*(batch[c].to_pylist() for c in ("rk", "doc", "text", "wanted"))):
        raw = (text or "").encode()
        for w in wanted:
            first, more = w["meta"] >> 18, (w["meta"] >> 10) & 255
            numbers.append((w["key"], w["lead"], w["crowded"], rk, doc, w["meta"]))
            covers.append(raw[first : first + more + LENGTH])
    return np.array(numbers, np.int64).reshape(-1, 6).T, covers


_BUCKETED = "bucket long, n int, numbers binary, covers binary"


def _bucket_rows(splitters: np.ndarray, parts: int, loud_buckets: int):
    """Suffixes by bucket of their leading token (a range, in ``parts`` by hash), those of a batch
    packed and compressed together. Crowded tokens' windows go to buckets of their own, under
    zero, by their hash."""

    def quiet(key, lead, rk, doc, meta, covers):
        bucket = np.searchsorted(splitters, lead, "right") * parts + (key.view(np.uint64) % np.uint64(parts)).astype(np.int64)
        for own in _groups(bucket, key):
            raw = b"".join([covers[i] for i in own])
            yield int(bucket[own[0]]), len(own), squeeze(np.concatenate([key[own], rk[own], doc[own], meta[own]])), zstandard.ZstdCompressor(level=3).compress(raw)

    def loud(rk, doc, meta, covers):
        for lo in range(0, len(covers), 1024):
            some = slice(lo, lo + 1024)
            spans = SpanHash(np.frombuffer(b"".join(covers[some]), np.uint8))
            which, _, at, nth = _windows(meta[some], covers[some])
            rows = np.zeros((len(_COLUMNS), len(at)), np.int64)
            # A hash of the whole window stands for token and cover.
            rows[0] = spans(at, at + LENGTH).view(np.int64)
            rows[RK], rows[DOC], rows[META] = rk[some][which], doc[some][which], _pack((meta[some][which] >> 18) + nth, 0, 0, 0)
            for settled in _settle(rows):
                own_rows = _rows(settled)
                bucket = -1 - (own_rows[0].view(np.uint64) % np.uint64(loud_buckets)).astype(np.int64)
                for own in _groups(bucket, own_rows[0]):
                    yield int(bucket[own[0]]), len(own), squeeze(own_rows[:, own].ravel()), None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            (key, lead, crowded, rk, doc, meta), covers = _covers(batch)
            calm, rest = np.flatnonzero(crowded == 0), np.flatnonzero(crowded)
            rows = [*quiet(key[calm], lead[calm], rk[calm], doc[calm], meta[calm], [covers[i] for i in calm]), *loud(rk[rest], doc[rest], meta[rest], [covers[i] for i in rest])]
            columns = list(zip(*rows)) or [()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, (pa.int64(), pa.int32(), pa.binary(), pa.binary()))], ["bucket", "n", "numbers", "covers"])

    return run


def _groups(bucket: np.ndarray, key: np.ndarray) -> list[np.ndarray]:
    """Element numbers by bucket, in the order of keys."""
    order = np.lexsort((key, bucket))
    return np.split(order, np.flatnonzero(np.diff(bucket[order])) + 1) if len(order) else []


def _windows(metas: np.ndarray, covers: list[bytes]):
    """Every window of the covers: its cover's number, place of the token in it, position in
    the joined bytes."""
    _, more, place, _ = _unpack(metas)
    lengths = np.fromiter(map(len, covers), np.int64, len(covers))
    begin = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    count = more + 1
    which = np.repeat(np.arange(len(covers)), count)
    nth = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
    return which, place[which] - nth, begin[which] + nth, nth


def _edge_bucket(table: pa.Table) -> pa.Table:
    """One bucket: its suffixes by leading token, whole groups compared some thousand at a time;
    or windows of crowded tokens, compared by their hash."""
    packed = list(zip(table["n"].to_pylist(), table["numbers"].to_pylist()))
    if table["covers"].null_count:
        rows = np.concatenate([swell(p, np.int64, len(_COLUMNS) * n).reshape(len(_COLUMNS), n) for n, p in packed], 1)
        done = (rows[META] & _SPAN) > 0
        spans = [_batch(rows[:, done])]
        rows = rows[:, ~done]
        order = np.argsort(rows[0], kind="stable")
        rows = rows[:, order]
        fresh = np.append(True, rows[0][1:] != rows[0][:-1]) if len(order) else np.zeros(0, bool)
        heads = np.flatnonzero(fresh)
        if len(heads):
            size = np.diff(np.append(heads, len(order)))
            twice = (size > 1) | (np.bitwise_or.reduceat((rows[META] >> 1) & 1, heads) > 0)
            spans.append(_span_batch(rows[:, np.repeat(twice, size)]))
        return pa.Table.from_batches(spans)
    numbers, covers = [], []
    for (n, raw_numbers), raw in zip(packed, table["covers"].to_pylist()):
        numbers.append(swell(raw_numbers, np.int64, 4 * n).reshape(4, n))
        length = LENGTH + ((numbers[-1][3] >> 10) & 255)
        data = zstandard.ZstdDecompressor().decompress(raw, max_output_size=int(length.sum()))
        ends = np.cumsum(length).tolist()
        covers += [data[i:j] for i, j in zip([0, *ends], ends)]
    key, rk, doc, meta = np.concatenate(numbers, 1)
    order = np.argsort(key, kind="stable")
    key, rk, doc, meta, covers = key[order], rk[order], doc[order], meta[order], [covers[i] for i in order]
    at, found = 0, []
    while at < len(key):
        # As many whole groups as fit in about 2048 covers, one at least.
        to = min(at + 2048, len(key))
        if to < len(key):
            whole = int(np.searchsorted(key, key[to]))
            to = whole if whole > at else int(np.searchsorted(key, key[to], "right"))
        found.append(_repeated_windows(key[at:to], rk[at:to], doc[at:to], meta[at:to], covers[at:to]))
        at = to
    return pa.Table.from_batches(found)


def _repeated_windows(key, rk, doc, meta, covers) -> pa.RecordBatch:
    """Spans of the windows that equal another of their group: same token at the same place."""
    data = np.frombuffer(b"".join(covers), np.uint8)
    which, place, at, nth = _windows(meta, covers)
    group = np.searchsorted(np.unique(key), key)[which] * 256 + place
    order = np.argsort(group, kind="stable")
    heads = np.flatnonzero(np.append(True, np.diff(group[order]) != 0)) if len(order) else order
    order, tied = multikey_quicksort(len(order), LENGTH // 8, lambda i, d: byte_words(data, at[i] + 8 * d), heads, np.diff(np.append(heads, len(order))), order)
    same = np.sort(order[tied])
    rows = np.zeros((len(_COLUMNS), len(same)), np.int64)
    rows[RK], rows[DOC] = rk[which[same]], doc[which[same]]
    start = (meta[which[same]] >> 18) + nth[same]
    return _span_batch(rows, start, start + LENGTH)


def repeated_spans(docs: DataFrame, crowd: int = CROWD, bucket: int = BUCKET) -> DataFrame:
    """(rk, doc, spans) for the texts of ``docs(rk, doc, text)`` that hold repeats; spans are
    (start, end) in bytes, unordered, and may overlap."""
    spark = docs.sparkSession
    # Two of each LENGTH - TOKEN windows begin with a new leading token, about.
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = max(shuffle_width(spark), 2 * size // (LENGTH - TOKEN) // bucket)
    rows = docs.mapInArrow(_suffix_rows, _ROW).repartitionByRange(buckets, *_COLUMNS[: _WORDS + 1])
    compared = materialise(rows.mapInArrow(_range_bucket, _ROW), "suffixes")
    is_span = F.col("meta").bitwiseAND(1) == 1
    as_span = lambda df: df.where(is_span).select("rk", "doc", F.shiftright("meta", 18).alias("start"), F.col("body").alias("end"))

    open_ = compared.where(~is_span).select(F.col("body").alias("key"), F.col("w0").alias("lead"), "rk", "doc", "meta")
    crowds = materialise(open_.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > crowd), "crowds")
    total = open_.count()
    found = as_span(compared)
    if total:
        loud = crowds.agg(F.sum("n")).first()[0] or 0
        ranges = max(1, min(RANGES, max(shuffle_width(spark), total // EDGE_BUCKET)))
        parts = -(-total // (EDGE_BUCKET * ranges))
        drawn = open_.select("lead").sample(min(1.0, SAMPLED * ranges / total), seed=5).limit(2 * SAMPLED * ranges).collect()
        keys = np.sort(np.array([r["lead"] for r in drawn], np.int64))
        splitters = np.unique(keys[np.arange(1, ranges) * len(keys) // ranges]) if len(keys) else keys
        marked = open_.join(crowds.select("key", F.lit(1).alias("crowded")), "key", "left").select("rk", "doc", F.struct("key", "lead", F.coalesce("crowded", F.lit(0)).alias("crowded"), "meta").alias("w"))
        wanted = marked.groupBy("rk", "doc").agg(F.collect_set("w").alias("wanted"))
        loud_buckets = max(shuffle_width(spark), loud // EDGE_BUCKET)
        dealt = docs.join(wanted, ["rk", "doc"]).select("rk", "doc", "text", "wanted").mapInArrow(_bucket_rows(splitters, parts, loud_buckets), _BUCKETED)
        found = found.unionByName(as_span(materialise(dealt.groupBy("bucket").applyInArrow(_edge_bucket, _ROW), "edges")))
    return found.groupBy("rk", "doc").agg(F.collect_set(F.struct("start", "end")).alias("spans"))


def kept_bytes(raw: bytes, spans) -> tuple[bytes, int]:
    """What the spans leave, and how many maximal runs they make."""
    if not spans:
        return raw, 0
    out, at, runs, end = [], 0, 0, -1
    for start, stop in sorted((s["start"], s["end"]) for s in spans):
        if start > end:
            runs += 1
            out.append(raw[at:start])
        end = max(end, stop)
        at = end
    out.append(raw[at:])
    return b"".join(out), runs


def _keyed(docs: DataFrame, rk: str = "rk", doc: str = "doc") -> DataFrame:
    """With a row's key and its id (a null's place taken by the least number)."""
    id_ = F.col("doc_id").cast("long")
    return docs.withColumns({rk: F.xxhash64(id_, F.coalesce(F.col("text"), F.lit(""))), doc: F.coalesce(id_, F.lit(-(1 << 63)))})


def repeat_digest(docs: DataFrame, crowd: int = CROWD, bucket: int = BUCKET) -> DataFrame:
    docs = _keyed(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for doc, text, spans in zip(batch["doc_id"].to_pylist(), batch["text"].to_pylist(), batch["spans"].to_pylist()):
                raw = text.encode()
                kept, runs = kept_bytes(raw, spans)
                rows.append((doc, len(raw), len(raw) - len(kept), runs, hashlib.sha256(kept).hexdigest()))
            columns = list(zip(*rows)) or [()] * 5
            names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
            yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in columns[:4]), pa.array(columns[4], pa.string())], names)

    joined = docs.join(repeated_spans(docs.select("rk", "doc", "text"), crowd, bucket), ["rk", "doc"], "left").select("doc_id", "text", "spans")
    return joined.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def remove_repeats(docs: DataFrame) -> DataFrame:
    """``docs`` with each text cut down to what stays (bytes of broken characters go too);
    ``n_chars``, where there is one, follows."""
    rk, doc, cut = (own_name(docs, f"{c} of the row") for c in ("key", "id", "spans"))
    keyed = _keyed(docs, rk, doc)
    found = repeated_spans(keyed.select(F.col(rk).alias("rk"), F.col(doc).alias("doc"), F.coalesce("text", F.lit("")).alias("text")))
    spans = found.select(F.col("rk").alias(rk), F.col("doc").alias(doc), F.col("spans").alias(cut))
    names = docs.columns
    joined = keyed.join(spans, [rk, doc], "left").select(*[F.col(f"`{c}`") for c in names], cut)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [t if t is None or not s else kept_bytes(t.encode(), s)[0].decode("utf-8", "ignore") for t, s in zip(batch["text"].to_pylist(), batch[cut].to_pylist())]
            new = {"text": pa.array(texts, batch.schema.field("text").type)}
            if "n_chars" in names:
                old = batch["n_chars"].to_pylist()
                new["n_chars"] = pa.array([len(t) if s and t is not None else o for t, s, o in zip(texts, batch[cut].to_pylist(), old)], batch.schema.field("n_chars").type)
            yield pa.RecordBatch.from_arrays([new.get(c, batch[c]) for c in names], names)

    return joined.mapInArrow(run, docs.schema)


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeat_digest(documents(spark, sf_dir, "doc_id", "text"))
