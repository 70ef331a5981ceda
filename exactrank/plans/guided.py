"""Exact quantiles in three rounds: approximate pivot, counts around it, repair of the gap.

Round 1 asks a sketch for a pivot for each target. Round 2 counts values below and equal to
each pivot in one scan. If the wanted rank lies among the equals the pivot is the answer. If
not, round 3 fetches the d values next to the pivot on the proper side; the farthest of them
is the answer. Values are never shuffled, only sketches, counts and candidates. A gap over
the budget is closed in by a bracket of two pivots first, so candidates stay bounded at
any size.
"""

from __future__ import annotations

import re
from collections.abc import Iterator, Sequence
from decimal import Decimal
from fractions import Fraction

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from exactrank.functions.kernels import NearestBuffer, nearest
from exactrank.functions.ranks import exact_share, rank_gap, target_rank
from exactrank.plans import pivot as pivots
from exactrank.plans.costmodel import suggest_eps
from exactrank.plans.ledger import MaxParam, RunLedger
from exactrank.plans.treemerge import FANOUT, tree
from exactrank.plans.values import FLOATING, kind_of, literal, value_column
from exactrank.sources.shared import scratch

EXTRACTS = ("auto", "topk", "kernel", "histogram", "persisted_split")
#: Candidates beyond which a bracket narrows the range first.
MAX_CANDIDATES = 100_000
#: Rows that all tasks together may send to the one that merges a top-k.
TOPK_ROWS = 2_000_000
#: Sketch entries that one task may merge; beyond, summaries are merged in a tree.
SKETCH_TUPLES = 20_000_000
COARSEST_EPS, FINEST_EPS = 1e-3, 1e-5


def expected_eps(values: DataFrame, max_candidates: int = MAX_CANDIDATES) -> float:
    """The sketch error that keeps the gap within the budget, from the planner's size of the input
    (no job): up to 1e10 values there is nothing to bracket."""
    width = 8 + values._jdf.schema().fields()[0].dataType().defaultSize()
    rows = max(1, int(str(values._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) // width)
    # Files are compressed, so there may be some times as many values.
    return min(COARSEST_EPS, max(FINEST_EPS, max_candidates / (8 * rows)))


def stored_once(values: DataFrame) -> DataFrame:
    """The one column as a table in the shared folder, if making it takes an exchange: the rounds
    then read it instead of making it again."""
    plan = values._jdf.queryExecution().executedPlan().toString()
    if "InMemoryTableScan" in plan or not re.search(r"(?<!Broadcast)(?<!Reused)Exchange ", plan):
        return values
    path, schema = scratch(values.sparkSession, "values"), values.schema
    values.write.parquet(path)
    return values.sparkSession.read.schema(schema).parquet(path)


class InputChanged(RuntimeError):
    """The two counts of one run differ."""


def sizes(values: DataFrame) -> tuple[int, int, object, object]:
    """Number of values, how many are NaN, least, greatest (NaN apart)."""
    nan = F.isnan("v") if isinstance(kind_of(values), FLOATING) else F.lit(False)
    v = F.when(~nan, F.col("v"))
    return tuple(values.agg(F.count("v"), F.count_if(nan), F.min(v), F.max(v)).first())


def count_around(values: DataFrame, around: Sequence) -> tuple[int, list[tuple[int, int]]]:
    """n, and (below, equal) for each pivot, in one scan; a few numbers for each task move."""
    kind = kind_of(values)
    v = F.col("v")
    wanted = [F.count("v")]
    for p in around:
        at = literal(p, kind)
        wanted += [F.count_if(v < at), F.count_if(v == at)]
    row = values.agg(*[c.alias(f"c{i}") for i, c in enumerate(wanted)]).first()
    return row[0], list(zip(row[1::2], row[2::2]))


def _beyond(kind: T.DataType, pivot, side: str) -> Column:
    if pivot is None:
        return F.lit(True)
    v, at = F.col("v"), literal(pivot, kind)
    return v > at if side == "right" else v < at


def by_topk(values: DataFrame, pivot, side: str, d: int) -> object:
    """Filter pushed to the scan, bounded heaps in each task, one merge task: no Python."""
    order = F.asc("v") if side == "right" else F.desc("v")
    near = values.where(_beyond(kind_of(values), pivot, side)).orderBy(order).limit(d)
    return near.agg((F.max if side == "right" else F.min)("v")).first()[0]


def by_histogram(values: DataFrame, pivot, side: str, d: int, far, most: int) -> object | None:
    """Candidates as (value, multiplicity): repeated values travel once. Only values up to ``far``
    are counted, and ``most`` of them come to the driver; None if the answer is not among them."""
    order = F.asc("v") if side == "right" else F.desc("v")
    beyond_far = _beyond(kind_of(values), far, side)
    counted = values.where(_beyond(kind_of(values), pivot, side) & ~beyond_far).groupBy("v").count().orderBy(order).limit(most)
    for r in counted.collect():
        d -= r["count"]
        if d <= 0:
            return r["v"]
    return None


def by_kernel(values: DataFrame, targets: Sequence[tuple], fanout: int = FANOUT, ledger: RunLedger | None = None) -> list:
    """All (pivot, side, d) in one scan: bounded buffers in each partition, then a tree."""
    peak = values.sparkSession.sparkContext.accumulator(0, MaxParam())
    kind = kind_of(values)
    wanted = [(side, d) for _, side, d in targets]
    conditions = [_beyond(kind, p, side) for p, side, _ in targets]
    any_ = conditions[0]
    for c in conditions[1:]:
        any_ = any_ | c
    marked = values.where(any_).select("v", *[c.alias(f"m{i}") for i, c in enumerate(conditions)])

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        buffers = [NearestBuffer(d, side) for side, d in wanted]
        for b in batches:
            for i, buffer in enumerate(buffers):
                buffer.add(b["v"].filter(b[f"m{i}"]))
        pid = TaskContext.get().partitionId()
        peak.add(sum(buffer.peak for buffer in buffers))
        for i, buffer in enumerate(buffers):
            got = buffer.result()
            if got is not None:
                yield pa.RecordBatch.from_arrays([pa.array([i] * len(got), pa.int32()), pa.array([pid] * len(got), pa.int32()), got], ["target", "pid", "v"])

    def together(table: pa.Table) -> pa.Table:
        side, d = wanted[table["target"][0].as_py()]
        kept = nearest(table["v"].combine_chunks(), d, side)
        return table.slice(0, len(kept)).set_column(2, "v", kept)

    schema = T.StructType([T.StructField("target", T.IntegerType()), T.StructField("pid", T.IntegerType()), T.StructField("v", kind)])
    rows = marked.mapInArrow(local, schema)
    last = tree(rows, values.rdd.getNumPartitions(), together, ("target",), fanout)
    ends = {r["target"]: (r["low"], r["high"]) for r in last.groupBy("target").agg(F.min("v").alias("low"), F.max("v").alias("high")).collect()}
    if ledger is not None:
        ledger.buffer_peak = max(ledger.buffer_peak, peak.value)
    return [ends[i][1 if side == "right" else 0] for i, (side, _) in enumerate(wanted)]


class _Run:
    """One run of the method on one column."""

    def __init__(self, values: DataFrame, eps: float | None, pivot: str, extract: str, merge: str, max_candidates: int, fanout: int, ledger: RunLedger):
        self.values, self.spark, self.kind = values, values.sparkSession, kind_of(values)
        self.eps, self.pivot, self.extract, self.merge = eps, pivot, extract, merge
        self.max_candidates, self.fanout, self.ledger = max_candidates, fanout, ledger
        self.parts = values.rdd.getNumPartitions()
        if pivot == "native":
            self.eps = eps or expected_eps(values, max_candidates)
            if self.parts / self.eps > SKETCH_TUPLES and pivots.supported("summary", self.kind):
                self.pivot = "summary"

    def ask(self, values: DataFrame, shares: list[Fraction]) -> list:
        return pivots.find(self.pivot, values, shares, self.eps, self.merge)

    def open(self, shares: list[Fraction]) -> list:
        """Round 1: sizes and pivots. One action where the sketch is an aggregate itself."""
        fused = self.pivot == "native" and pivots.supported("native", self.kind)
        with self.ledger.round(self.spark, "pivot"):
            if fused:
                nan = F.isnan("v") if isinstance(self.kind, FLOATING) else F.lit(False)
                v = F.when(~nan, F.col("v"))
                row = self.values.agg(F.count("v"), F.count_if(nan), F.min(v), F.max(v), F.percentile_approx(v, [float(q) for q in shares], round(1 / self.eps))).first()
                self.n, self.nan, self.least, self.greatest = row[:4]
                found = list(row[4]) if row[4] is not None else []
            else:
                self.n, self.nan, self.least, self.greatest = sizes(self.values)
                self.eps = self.eps or suggest_eps(self.n, self.parts)[0]
                found = self.ask(self.values, shares)
        self.ledger.n, self.ledger.partitions, self.ledger.eps = self.n, self.parts, self.eps
        self.solid = self.n - self.nan
        return found

    def solve(self, ranks: dict[int, object]) -> dict[int, object]:
        """Values of 0-based ranks among the non-NaN values, each with its pivot."""
        out = {}
        with self.ledger.round(self.spark, "count"):
            around = list(dict.fromkeys(ranks.values()))
            n, counts = count_around(self.values, around)
        if n != self.n:
            raise InputChanged(f"{self.n} values, then {n}: the input must stay the same during a run")
        where = dict(zip(around, counts))
        far = []
        for k, p in ranks.items():
            side, d = rank_gap(k, *where[p])
            self.ledger.rank_err = max(self.ledger.rank_err, d)
            if side == "hit":
                out[k] = p
            else:
                far.append((k, p, side, d))
        near = [t for t in far if t[3] <= self.max_candidates]
        for k, p, side, d in (t for t in far if t[3] > self.max_candidates):
            out[k] = self.bracket(k, where[p], p, side)
        if near:
            out |= self.repair(near)
        return out

    def repair(self, near: list[tuple]) -> dict[int, object]:
        """Round 3."""
        biggest = max(d for *_, d in near)
        self.ledger.candidates = max(self.ledger.candidates, biggest)
        how = self.extract
        if how == "auto":
            # A top-k merges what all tasks send in one task; the kernel does so in a tree.
            how = "topk" if len(near) == 1 and biggest * self.parts <= TOPK_ROWS else "kernel"
        if how == "kernel" and isinstance(self.kind, T.StructType):
            how = "topk"
        self.ledger.notes["extract"] = how
        with self.ledger.round(self.spark, "extract"):
            if how == "kernel":
                got = by_kernel(self.values, [t[1:] for t in near], self.fanout, self.ledger)
                return {k: x for (k, *_), x in zip(near, got)}
            if how == "persisted_split":
                return self.from_split(near)
            if how == "histogram":
                return {t[0]: self.from_histogram(*t) for t in near}
            return {k: by_topk(self.values, p, side, d) for k, p, side, d in near}

    def from_histogram(self, k: int, p, side: str, d: int) -> object:
        """Counted values between the pivot and a sketched bound beyond the rank."""
        share, margin = Fraction(2 * k + 1, 2 * self.solid), 2 * Fraction(str(self.eps)) + Fraction(1, self.solid)
        (far,) = self.ask(self.values, [min(share + margin, Fraction(1)) if side == "right" else max(share - margin, Fraction(0))])
        found = by_histogram(self.values, p, side, d, far, self.max_candidates)
        return by_kernel(self.values, [(p, side, d)], self.fanout, self.ledger)[0] if found is None else found

    def from_split(self, near: list[tuple]) -> dict[int, object]:
        """The counted split, kept: later scans read only the side they need."""
        out = {}
        for k, p, side, d in near:
            split = self.values.where(_beyond(self.kind, p, side)).persist()
            self.ledger.persists += 1
            try:
                out[k] = by_topk(split, p, side, d)
            finally:
                split.unpersist()
        return out

    def bracket(self, k: int, counts: tuple[int, int], p, side: str) -> object:
        """Narrow to the values between two sketched bounds until the rest fits the budget. Each
        level leaves about 4 eps of the values, so levels are few at any size."""
        base = self.values.where(~F.isnan("v")) if isinstance(self.kind, FLOATING) else self.values
        below, equal = counts
        if side == "right":
            inside, rank, size = base.where(_beyond(self.kind, p, "right")), k - below - equal, self.solid - below - equal
        else:
            inside, rank, size = base.where(_beyond(self.kind, p, "left")), k, below
        while size > self.max_candidates:
            share, margin = Fraction(2 * rank + 1, 2 * size), Fraction(str(2 * self.eps)) + Fraction(1, size)
            lo_q, hi_q = max(share - margin, Fraction(0)), min(share + margin, Fraction(1))
            with self.ledger.round(self.spark, "bracket"):
                lo, hi = self.ask(inside, [lo_q, hi_q])
            with self.ledger.round(self.spark, "count"):
                _, ((lo_b, lo_e), (hi_b, hi_e)) = count_around(inside, [lo, hi])
            for x, b, e in ((lo, lo_b, lo_e), (hi, hi_b, hi_e)):
                if b <= rank < b + e:
                    return x
            if rank < lo_b:
                inside, new = inside.where(_beyond(self.kind, lo, "left")), lo_b
            elif rank >= hi_b + hi_e:
                inside, rank, new = inside.where(_beyond(self.kind, hi, "right")), rank - hi_b - hi_e, size - hi_b - hi_e
            else:
                inside = inside.where(_beyond(self.kind, lo, "right") & _beyond(self.kind, hi, "left"))
                rank, new = rank - lo_b - lo_e, hi_b - lo_b - lo_e
            if new >= size:
                # Bounds that exclude nothing, from a provider that missed the column's type.
                from exactrank.plans.prune import select_rank

                return select_rank(inside, rank, "agg", ledger=self.ledger)
            size = new
        self.ledger.candidates = max(self.ledger.candidates, size)
        with self.ledger.round(self.spark, "extract"):
            if (rank + 1) * self.parts <= TOPK_ROWS or isinstance(self.kind, T.StructType):
                return by_topk(inside, None, "right", rank + 1)
            return by_kernel(inside, [(None, "right", rank + 1)], self.fanout, self.ledger)[0]


def _fused(run: _Run, targets: list) -> dict[int, object] | None:
    """Two rounds: bounds from the sketch on both sides, then ONE scan that counts below and
    gathers the window as (value, multiplicity). None if a rank fell outside its window."""
    out = {}
    for q, k in targets:
        margin = 2 * Fraction(str(run.eps)) + Fraction(2, max(run.solid, 1))
        with run.ledger.round(run.spark, "pivot"):
            lo, hi = run.ask(run.values, [max(q - margin, Fraction(0)), min(q + margin, Fraction(1))])
        a, b = literal(lo, run.kind), literal(hi, run.kind)
        v = F.col("v")
        with run.ledger.round(run.spark, "count and extract"):
            zone = F.when(v < a, 0).when(v <= b, 1)
            rows = run.values.where(v <= b).groupBy(zone.alias("zone"), F.when(zone == 1, v).alias("v")).count()
            rows = rows.orderBy("zone", "v").limit(run.max_candidates + 2).collect()
        at = sum(r["count"] for r in rows if r["zone"] == 0)
        found = at > k
        for r in rows:
            if r["zone"] == 1:
                if at <= k < at + r["count"]:
                    out[k], found = r["v"], False
                    break
                at += r["count"]
        else:
            return None
        if found:
            return None
        run.ledger.candidates = max(run.ledger.candidates, len(rows))
    return out


def result_frame(spark, rows: list[tuple], kind: T.DataType, interpolated: bool) -> DataFrame:
    out = T.DoubleType() if interpolated else kind
    schema = T.StructType([T.StructField("q", T.DoubleType()), T.StructField("k", T.LongType()), T.StructField("value", out)])
    return spark.createDataFrame([(q, k, v + 0.0 if isinstance(v, float) else v) for q, k, v in rows], schema)


def quantile_values(
    df: DataFrame, col: str | Column, q, *, eps: float | None = None, rule: str = "nearest", pivot: str = "native", extract: str = "auto", merge: str = "tree",
    nan_policy: str = "last", rounds: int = 3, max_candidates: int = MAX_CANDIDATES, fanout: int = FANOUT, store: bool = True, ledger: RunLedger | None = None,
) -> list[tuple]:
    """(q, 0-based rank, value) for each q, as Python values. ``store``: write the column once
    where making it takes an exchange."""
    if extract not in EXTRACTS:
        raise ValueError(f"no extraction {extract!r}")
    ledger = ledger if ledger is not None else RunLedger()
    ledger.method = ledger.method or "guided"
    shares = [exact_share(x) for x in (q if isinstance(q, (list, tuple)) else [q])]
    names = [float(s) for s in shares]
    values = value_column(df, col, nan_policy)
    run = _Run(stored_once(values) if store else values, eps, pivot, extract, merge, max_candidates, fanout, ledger)
    found = run.open(shares)
    if nan_policy == "error" and run.nan:
        raise ValueError(f"{run.nan} values are NaN")
    targets = [target_rank(run.n, s, rule) for s in shares]
    if not run.n:
        return [(x, None, None) for x in names]
    found_at: dict[int, object] = {}
    open_ranks: dict[int, object] = {}
    for i, t in enumerate(targets):
        for k in {t.low, t.high}:
            if k >= run.solid:
                found_at[k] = float("nan")
            elif k == 0:
                found_at[k] = run.least
            elif k == run.solid - 1:
                found_at[k] = run.greatest
            else:
                open_ranks[k] = found[i]
    if open_ranks and rounds == 2:
        got = _fused(run, [(Fraction(2 * k + 1, 2 * run.solid), k) for k in open_ranks])
        if got is not None:
            found_at |= got
            open_ranks = {}
    if open_ranks:
        found_at |= run.solve(open_ranks)
    out = []
    for x, t in zip(names, targets):
        a = found_at[t.low]
        if rule in ("midpoint", "linear"):
            a, b = float(a), float(found_at[t.high])
            a = a + (b - a) * float(t.weight) if t.weight else a
        out.append((x, t.low, a))
    return out


def guided_quantile(df: DataFrame, col: str | Column, q, **options) -> DataFrame:
    """Exact quantiles of a column: a DataFrame (q, k, value), value of the column's own type
    (double for the rules that interpolate). Null if there are no values."""
    values = value_column(df, col, options.get("nan_policy", "last"))
    rows = quantile_values(df, col, q, **options)
    return result_frame(df.sparkSession, rows, kind_of(values), options.get("rule") in ("midpoint", "linear"))


def verify(df: DataFrame, col: str | Column, answers: Sequence[tuple], ledger: RunLedger) -> bool:
    """Whether the (k, value) given stand at their ranks, by one count around them; kept in the
    ledger with the greatest distance."""
    n, counts = count_around(value_column(df, col), [v for _, v in answers])
    off = [max(0, below - k, k - (below + equal - 1)) if equal else n for (k, _), (below, equal) in zip(answers, counts)]
    ledger.exact = not any(off)
    ledger.notes["distance"] = max(off, default=0)
    return ledger.exact


def guided_median(df: DataFrame, col: str | Column, **options) -> Decimal | float | None:
    return quantile_values(df, col, "0.5", **options)[0][2]
