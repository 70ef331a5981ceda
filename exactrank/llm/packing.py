"""Best-fit packing of token pieces by exact complements.

Every document is cut into full pieces and at most one shorter one, so packing needs only how
many pieces there are of each length: at most ``capacity`` numbers, however large the corpus.
The driver plans on these counts. A plan is a list of patterns, each with how many sequences
use it; the longest length in stock is completed by a single length, a pair or a triple that
fills its gap exactly, looked up in an index of sums and taken as often as stock allows; what
has no exact complement is placed by best fit over open sequences. Pieces are then numbered
within their length, and a number's sequence and offset follow from the plan by binary search.

Defined results: a null text is empty (one piece, the end token); repeated rows are packed
each; an empty table gives no rows; null doc_ids are packed like others; extra columns are
ignored.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from exactrank.llm.chunks import byte_bpe_encoder, uncollected
from exactrank.llm.common import documents, materialise

CAPACITY = 1024
END_ID = 2
#: Pieces of one length are numbered in groups of about so many rows.
GROUP_ROWS = 200_000

_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def cut_lengths(n: int, capacity: int) -> list[int]:
    """Piece lengths of a document of n tokens: full ones after a first that may be shorter."""
    first = (n - 1) % capacity + 1
    return [first] + [capacity] * ((n - first) // capacity)


def token_pieces(docs: DataFrame, tokenizer: str, end_id: int = END_ID, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """One row per piece of each text of ``docs(doc_id, text)``, with its ids if asked for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = byte_bpe_encoder(tokenizer)
        end = np.array([end_id], "<u4")
        with uncollected():
            for batch in batches:
                rows: list[tuple] = []
                for doc, text in zip(batch["doc_id"].to_pylist(), batch["text"]):
                    ids = np.concatenate([encode(text.as_py() or ""), end])
                    at = 0
                    for piece, length in enumerate(cut_lengths(len(ids), capacity)):
                        own = ids[at : at + length].tobytes()
                        rows.append((doc, piece, at, length, zlib.crc32(own), own if with_ids else None))
                        at += length
                columns = list(zip(*rows)) or [()] * 6
                kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
                names = ["doc_id", "piece", "start", "length", "ids_crc32", "ids"]
                keep = 6 if with_ids else 5
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in list(zip(columns, kinds))[:keep]], names[:keep])
        encode.forget()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, _PIECES + (", ids binary" if with_ids else ""))


class SumIndex:
    """Which singles, pairs and triples of lengths in stock add up to a sum, longest part first.

    Pairs are listed under their sum; a triple is a length and a pair listed under the rest.
    Stock only shrinks, and a gap always stands beside the same length, so a combination that
    is short once stays short: each sum keeps a place in its list and never looks back.
    """

    def __init__(self, counts: dict[int, int], capacity: int):
        self.left = {n: c for n, c in counts.items() if c > 0}
        self.capacity = capacity
        lengths = np.array(sorted(self.left, reverse=True), np.int64)
        a, b = (lengths[i] for i in np.triu_indices(len(lengths)))
        fits = a + b <= capacity
        a, b = a[fits], b[fits]
        order = np.lexsort((-a, a + b))
        a, b = a[order], b[order]
        cuts = np.searchsorted(a + b, np.arange(capacity + 2))
        self.lengths = lengths.tolist()
        self.pairs = {s: list(zip(a[i:j].tolist(), b[i:j].tolist())) for s, (i, j) in enumerate(zip(cuts, cuts[1:])) if j > i}
        self._pair_at: dict[int, int] = {}
        self._triples: dict[int, Iterator[tuple[int, int, int]]] = {}
        self._triple: dict[int, tuple[int, int, int] | None] = {}

    def take(self, pattern: tuple[int, ...], times: int) -> None:
        for n in pattern:
            self.left[n] -= times
            if not self.left[n]:
                del self.left[n]

    def times(self, pattern: tuple[int, ...]) -> int:
        """How often a pattern can be taken whole."""
        return min(self.left.get(n, 0) // pattern.count(n) for n in set(pattern))

    def _triples_of(self, total: int) -> Iterator[tuple[int, int, int]]:
        for a in self.lengths:
            if 3 * a < total:
                return
            if a in self.left:
                for b, c in self.pairs.get(total - a, ()):
                    if b <= a:
                        yield a, b, c

    def complement(self, first: int) -> tuple[int, ...] | None:
        """What fills the gap beside ``first`` exactly."""
        gap = self.capacity - first
        if self.times((first, gap)):
            return (gap,)
        pairs, at = self.pairs.get(gap, ()), self._pair_at.get(gap, 0)
        while at < len(pairs) and not self.times((first, *pairs[at])):
            at += 1
        self._pair_at[gap] = at
        if at < len(pairs):
            return pairs[at]
        if gap not in self._triples:
            self._triples[gap] = self._triples_of(gap)
            self._triple[gap] = next(self._triples[gap], None)
        while (found := self._triple[gap]) is not None and not self.times((first, *found)):
            self._triple[gap] = next(self._triples[gap], None)
        return found


def best_fit(counts: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Best fit in decreasing length over open sequences, many equal ones at a time: each piece
    goes where the least room is left, a new sequence opens only if none has room."""
    open_: dict[int, dict[tuple[int, ...], int]] = {}  # by room left: pattern, how many sequences
    rooms: list[int] = []  # in order

    def put(room: int, pattern: tuple[int, ...], times: int) -> None:
        if room not in open_:
            open_[room] = {}
            insort(rooms, room)
        open_[room][pattern] = open_[room].get(pattern, 0) + times

    for n in sorted(counts, reverse=True):
        rest = counts[n]
        while rest:
            i = bisect_left(rooms, n)
            if i == len(rooms):
                break
            room = rooms[i]
            pattern, have = open_[room].popitem()
            if not open_[room]:
                del open_[room], rooms[i]
            # A sequence that takes one piece has the least room again, until it is full.
            each = min(room // n, rest)
            used = min(have, rest // each)
            rest -= used * each
            put(room - each * n, pattern + (n,) * each, used)
            if have > used:
                put(room, pattern, have - used)
        per = capacity // n
        if rest // per:
            put(capacity - per * n, (n,) * per, rest // per)
        if rest % per:
            put(capacity - rest % per * n, (n,) * (rest % per), 1)
    return [(pattern, times) for room in rooms for pattern, times in open_[room].items()]


def plan_packing(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[tuple[int, ...], int]]:
    """(lengths in a sequence, number of such sequences), using each piece once.

    Work depends on the number of distinct lengths, not of pieces: each step takes its pattern
    as often as stock allows, which uses up a length. What has no exact complement left is
    placed by best fit.
    """
    full, index = counts.get(capacity, 0), SumIndex({n: c for n, c in counts.items() if n < capacity}, capacity)
    plan = [((capacity,), full)] if full else []
    residual: dict[int, int] = {}
    for first in index.lengths:
        while first in index.left:
            found = index.complement(first)
            if found is None:
                # Shorter lengths may still want this one as a part, but each such pattern would
                # have been found from here.
                residual[first] = index.left[first]
                index.take((first,), index.left[first])
                break
            pattern = (first, *found)
            times = index.times(pattern)
            plan.append((pattern, times))
            index.take(pattern, times)
    return plan + best_fit(residual, capacity)


def placements(plan: list[tuple[tuple[int, ...], int]]) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """By length: the first piece number of each run, the run's first sequence, its offset.
    The pieces of a run go to consecutive sequences."""
    runs: dict[int, list[tuple[int, int, int]]] = {}
    used: dict[int, int] = {}
    sequence = 0
    for pattern, times in plan:
        offset = 0
        for n in pattern:
            runs.setdefault(n, []).append((used.get(n, 0), sequence, offset))
            used[n] = used.get(n, 0) + times
            offset += n
        sequence += times
    return {n: tuple(np.array(c, np.int64) for c in zip(*r)) for n, r in runs.items()}


def place(pieces: DataFrame, capacity: int = CAPACITY, order: tuple[str, ...] = ("doc_id", "piece", "start", "ids_crc32")) -> DataFrame:
    """``pieces`` with sequence_id and offset. Reads ``pieces`` twice, so hand in a stored table."""
    spark = pieces.sparkSession
    counted = pieces.groupBy("length").count().collect()  # at most ``capacity`` rows
    counts = {r["length"]: r["count"] for r in counted}
    table = spark.sparkContext.broadcast(placements(plan_packing(counts, capacity)))
    groups = max(32, sum(counts.values()) // GROUP_ROWS)

    # Numbers within a length: within (length, group) by a window, plus the sizes of the groups before.
    grouped = pieces.withColumn("_group", F.pmod(F.xxhash64(*order), F.lit(groups)).cast("int"))
    sizes = grouped.groupBy("length", "_group").count()
    before = Window.partitionBy("length").orderBy("_group").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select("length", "_group", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("_start"))
    nth = F.row_number().over(Window.partitionBy("length", "_group").orderBy(*order)) - 1
    numbered = grouped.withColumn("_nth", nth).join(starts, ["length", "_group"]).withColumn("_nth", F.col("_nth") + F.col("_start"))
    out = numbered.drop("_group", "_start")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, number = batch["length"].to_numpy(), batch["_nth"].to_numpy()
            sequence, offset = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            for n in np.unique(length):
                own = length == n
                first, start, at = table.value[int(n)]
                r = np.searchsorted(first, number[own], "right") - 1
                sequence[own] = start[r] + number[own] - first[r]
                offset[own] = at[r]
            kept = [c for c in batch.schema.names if c != "_nth"]
            yield pa.RecordBatch.from_arrays([*(batch[c] for c in kept), pa.array(sequence), pa.array(offset)], [*kept, "sequence_id", "offset"])

    schema = out.drop("_nth").schema.add("sequence_id", "long").add("offset", "long")
    return out.mapInArrow(run, schema).select(*pieces.columns, "sequence_id", "offset")


def pack_documents(docs: DataFrame, tokenizer: str | None = None, end_id: int = END_ID, capacity: int = CAPACITY) -> DataFrame:
    """Every text of ``docs(doc_id, text)`` in pieces of at most ``capacity`` tokens, placed."""
    import public_tokenizers

    found = token_pieces(docs, tokenizer or public_tokenizers.path("byte_bpe_50k.json"), end_id, capacity)
    return place(materialise(found, "pieces"), capacity)


def op5_complement_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(documents(spark, sf_dir, "doc_id", "text"))
