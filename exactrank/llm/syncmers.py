"""Document fingerprints from closed syncmers.

A k-byte string is an anchor if the smallest hash of its inner s-byte strings is the first's
or the last's. Whether it is one depends on nothing around it, so an edit moves only the
anchors it touches. A fingerprint keeps the anchors of smallest hash with their byte
positions; likeness counts shared anchors on the longest chain that stands in the same order in
both texts, however far edits before them shift it, as the share of the two texts that is alike.

Documents meet their neighbour in one exchange of texts: doc_id is cut at sampled quantiles
into bounded slices, and the first row of each slice also goes to the slice before it.

Defined results: a null text is empty; an empty text has the fingerprint "" and is like
another empty one (1) and no other text (0); a text under k bytes is one anchor, the whole of
it; equal texts have equal fingerprints; null doc_ids come last; rows with equal doc_id are in
the order of their texts; one row alone is its own neighbour; an empty table gives no rows.
"""

from __future__ import annotations

import base64
import hashlib
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from exactrank.llm.common import documents, shuffle_width
from exactrank.llm.textkernel import SpanHash, mix, pieces

K, S = 16, 8
#: Anchors that a fingerprint keeps: the likeness of 64 has a standard error of about 0.06.
ANCHORS = 64

Sketch = tuple[np.ndarray, np.ndarray]


def _inner_hashes(data: np.ndarray) -> np.ndarray:
    """A mixed hash of each 8-byte string."""
    x = data.astype(np.uint64)
    for shift in (1, 2, 4):
        x = x[:-shift] | (x[shift:] << np.uint64(8 * shift))
    return mix(x)


def syncmers(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions and 64-bit hashes of the closed syncmers of a byte string (k=16, s=8)."""
    if len(data) < K:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    h = _inner_hashes(data)
    low = h
    for step in (1, 2, 4):
        low = np.minimum(low[:-step], low[step:])
    low = np.minimum(low[:-1], low[1:])
    n = len(data) - K + 1
    at = np.flatnonzero((h[:n] == low) | (h[K - S : K - S + n] == low))
    return at, mix(h[at] * np.uint64(0xD6E8FEB86659FD93) + h[at + K - S])


def sketches(texts: list[bytes], anchors: int = ANCHORS) -> list[Sketch]:
    """For each text its anchors of smallest hash (32 bits), by hash, with positions.

    The n-th occurrence of a repeated anchor is an anchor of its own, so repetition counts.
    """
    out: list[Sketch] = []
    lengths = np.fromiter((len(t) for t in texts), np.int64, len(texts))
    offs = np.concatenate([[0], np.cumsum(lengths)])
    data = np.frombuffer(b"".join(texts), np.uint8)
    for lo, hi, part, cut in pieces(data, offs):
        at, h = syncmers(part)
        row = np.searchsorted(cut, at, "right") - 1
        inside = at + K <= cut[row + 1]
        at, h, row = at[inside], h[inside], row[inside]
        order = np.lexsort((at, h, row))
        at, h, row = at[order], h[order], row[order]
        fresh = np.ones(len(h), bool)
        fresh[1:] = (h[1:] != h[:-1]) | (row[1:] != row[:-1])
        nth = np.arange(len(h)) - np.maximum.accumulate(np.where(fresh, np.arange(len(h)), 0))
        h32 = (mix(h + nth.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(32)).astype(np.uint32)
        bounds = np.searchsorted(row, np.arange(hi - lo + 1))
        rel = at - cut[row]
        short = [i for i in range(hi - lo) if bounds[i] == bounds[i + 1] and cut[i] < cut[i + 1]]
        whole = dict(zip(short, SpanHash(part)(cut[short], cut[np.add(short, 1)]))) if short else {}
        for i in range(hi - lo):
            a, p = h32[bounds[i] : bounds[i + 1]], rel[bounds[i] : bounds[i + 1]]
            if i in whole:
                a, p = np.array([whole[i] >> np.uint64(32)], np.uint32), np.zeros(1, np.int64)
            if len(a) > anchors:
                keep = np.argpartition(a, anchors)[:anchors]
                a, p = a[keep], p[keep]
            by = np.argsort(a, kind="stable")
            out.append((a[by], p[by].astype(np.uint32)))
    return out


def to_string(sketch: Sketch) -> str:
    return base64.b64encode(np.concatenate(sketch).tobytes()).decode() if len(sketch[0]) else ""


def from_string(fingerprint: str) -> Sketch:
    both = np.frombuffer(base64.b64decode(fingerprint), np.uint32)
    return both[: len(both) // 2], both[len(both) // 2 :]


def _chain(p: np.ndarray, q: np.ndarray) -> int:
    """Length of the longest chain of pairs of positions that rises in both."""
    ends: list[int] = []  # the smallest last position of a chain of each length
    for v in q[np.lexsort((-q.astype(np.int64), p))].tolist():
        at = bisect_left(ends, v)
        ends[at : at + 1] = [v]
    return len(ends)


def likeness(x: Sketch, y: Sketch, anchors: int = ANCHORS) -> float:
    """Share of the texts that is alike, 0 to 1, from the smallest hashes of both together."""
    (a, p), (b, q) = x, y
    if not len(a) or not len(b):
        return float(len(a) == len(b))
    both = np.union1d(a, b)
    if len(a) >= anchors or len(b) >= anchors:
        both = both[:anchors]
    last = both[-1]
    common, i, j = np.intersect1d(a[a <= last], b[b <= last], return_indices=True)
    if not len(common):
        return 0.0
    jaccard = _chain(p[i], q[j]) / len(both)
    return 2 * jaccard / (1 + jaccard)


def edited(text: str, following: str) -> str:
    """The last third (rounded down) gives way to as much of the start of the next text."""
    n = len(text) // 3
    return text[: len(text) - n] + following[:n]


_OUT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _slices(docs: DataFrame, parts: int) -> tuple[list[int], list[int | None]]:
    """Cuts of doc_id (descending) and the first id in each slice: two scans of that column,
    a result of at most ``parts`` numbers each."""
    ids = docs.select("doc_id").where("doc_id IS NOT NULL")
    cuts = sorted({int(c) for c in ids.approxQuantile("doc_id", [i / parts for i in range(1, parts)], 0.25 / parts)}, reverse=True) if parts > 1 else []
    heads = dict(docs.select(_slice_of(cuts).alias("s"), "doc_id").groupBy("s").agg(F.max("doc_id")).collect())
    return cuts, [heads.get(s, "none") for s in range(len(cuts) + 1)]


def _slice_of(cuts: list[int]):
    """Slice number: how many cuts are above the id; null ids are in the last slice."""
    if not cuts:
        return F.lit(0)
    up = F.array(*[F.lit(c) for c in reversed(cuts)])
    inner = F.aggregate(
        F.sequence(F.lit(1), F.lit(len(cuts).bit_length())),
        F.struct(F.lit(0).alias("lo"), F.lit(len(cuts)).alias("hi")),
        lambda s, _: F.when(s["lo"] >= s["hi"], s).otherwise(
            F.when(
                F.element_at(up, (F.floor((s["lo"] + s["hi"]) / 2) + 1).cast("int")) <= F.col("doc_id"),
                F.struct((F.floor((s["lo"] + s["hi"]) / 2) + 1).cast("int").alias("lo"), s["hi"].alias("hi")),
            ).otherwise(F.struct(s["lo"].alias("lo"), F.floor((s["lo"] + s["hi"]) / 2).cast("int").alias("hi")))
        ),
    )["lo"]
    return F.when(F.col("doc_id").isNull(), F.lit(len(cuts))).otherwise(F.lit(len(cuts)) - inner)


def _neighbours(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come by slice, in order, each slice's guest row last."""
    held: tuple | None = None
    for batch in batches:
        rows = list(zip(batch["slice"].to_pylist(), batch["guest"].to_pylist(), batch["doc_id"].to_pylist(), (t or "" for t in batch["text"].to_pylist())))
        if held is not None:
            rows.insert(0, held)
        held = rows[-1] if rows else held
        for at in range(0, len(rows) - 1, 256):
            part = rows[at : at + 257]
            prints = sketches([r[3].encode() for r in part])
            todo = [i for i in range(len(part) - 1) if not part[i][1] and part[i + 1][0] == part[i][0]]
            changed = [edited(part[i][3], part[i + 1][3]).encode() for i in todo]
            after = sketches(changed)
            if todo:
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([part[i][2] for i in todo], pa.int64()),
                        pa.array([len(part[i][3]) for i in todo], pa.int64()),
                        pa.array([hashlib.sha256(c).hexdigest() for c in changed]),
                        pa.array([to_string(prints[i]) for i in todo]),
                        pa.array([to_string(s) for s in after]),
                        pa.array([likeness(prints[i], s) for i, s in zip(todo, after)]),
                        pa.array([likeness(prints[i], prints[i + 1]) for i in todo]),
                    ],
                    ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
                )


def fingerprint_neighbours(docs: DataFrame, parts: int | None = None) -> DataFrame:
    """Fingerprints of each text of ``docs(doc_id, text)``, of its edited form, and likeness
    to that form and to the next text in descending doc_id."""
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    parts = parts or max(shuffle_width(spark), docs.rdd.getNumPartitions())
    cuts, heads = _slices(docs, parts)
    filled = [s for s, h in enumerate(heads) if h != "none"]
    # The head of each filled slice is a guest in the filled slice before it, the first of all in the last.
    hosts = {filled[(i + 1) % len(filled)]: s for i, s in enumerate(filled)}
    table = [(s, heads[s], host) for s, host in hosts.items()]
    guests = F.broadcast(spark.createDataFrame(table, "s int, head long, host int"))
    sliced = docs.withColumn("s", _slice_of(cuts).cast("int"))
    marked = sliced.join(guests, "s", "left")
    head = F.col("head").eqNullSafe(F.col("doc_id")) & F.col("host").isNotNull()
    own = F.struct(F.col("s").alias("slice"), F.lit(False).alias("guest"))
    both = F.when(head, F.array(own, F.struct(F.col("host").alias("slice"), F.lit(True).alias("guest")))).otherwise(F.array(own))
    rows = marked.select("doc_id", "text", F.explode(both).alias("p")).select("p.*", "doc_id", "text")
    ordered = rows.repartition(parts, "slice").sortWithinPartitions("slice", "guest", F.desc_nulls_last("doc_id"), "text")
    return ordered.mapInArrow(_neighbours, _OUT)


def op1_syncmer_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint_neighbours(documents(spark, sf_dir, "doc_id", "text"))
