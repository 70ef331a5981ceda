"""Approximate pivots. Whatever the provider returns, the method above it stays exact: a
pivot only decides how far the answer is from it."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from fractions import Fraction

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from exactrank.functions.summaries import BufferedSummary, RankSummary, fold_left, tree_merge
from exactrank.plans.treemerge import FANOUT, tree
from exactrank.plans.values import FLOATING, NUMERIC, TEMPORAL, kind_of

PROVIDERS = ("native", "stat", "summary", "kll", "sample")
SAMPLE_ROWS = 4000


def supported(provider: str, kind: T.DataType) -> bool:
    if provider == "native":
        return isinstance(kind, (*NUMERIC, *TEMPORAL)) and not isinstance(kind, T.DayTimeIntervalType)
    if provider in ("stat", "summary", "kll"):
        return isinstance(kind, NUMERIC)
    return provider == "sample"


def _plain(values: DataFrame) -> DataFrame:
    """Without NaN, which no sketch orders reliably."""
    return values.where(~F.isnan("v")) if isinstance(kind_of(values), FLOATING) else values


def _back(x, kind: T.DataType):
    """A double from a sketch as a value of the column's type."""
    if x is None or isinstance(kind, FLOATING):
        return x
    if isinstance(kind, T.DecimalType):
        from decimal import Decimal

        return Decimal(repr(x)).quantize(Decimal(1).scaleb(-kind.scale))
    return int(x)


def native(values: DataFrame, shares: Sequence[Fraction], eps: float, merge: str = "tree") -> list:
    """Spark's own mergeable sketch, one aggregate."""
    row = _plain(values).agg(F.percentile_approx("v", [float(q) for q in shares], max(1, round(1 / eps))).alias("p")).first()
    return list(row["p"]) if row["p"] is not None else []


def stat(values: DataFrame, shares: Sequence[Fraction], eps: float, merge: str = "tree") -> list:
    """Spark's statistics function: per-partition summaries with a head buffer."""
    kind = kind_of(values)
    found = _plain(values).select(F.col("v").cast("double").alias("v")).approxQuantile("v", [float(q) for q in shares], eps)
    return [_back(x, kind) for x in found]


def summary_rows(values: DataFrame, eps: float, make=BufferedSummary) -> DataFrame:
    """(pid, payload): one serialised summary for each partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = make(eps)
        for b in batches:
            s.insert_many(b["v"].to_numpy(zero_copy_only=False))
        done = s.summary()
        if done.n:
            yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()], pa.int32()), pa.array([done.to_bytes()])], ["pid", "payload"])

    return _plain(values).select(F.col("v").cast("double").alias("v")).mapInArrow(run, "pid int, payload binary")


def merged_summary(values: DataFrame, eps: float, merge: str = "tree", make=BufferedSummary, fanout: int = FANOUT) -> RankSummary | None:
    """One summary of all values: merged in a tree on the executors, or on the driver (``driver``:
    one after another, ``driver-tree``: pairwise)."""
    rows = summary_rows(values, eps, make)

    def together(table: pa.Table) -> pa.Table:
        one = tree_merge(RankSummary.from_bytes(p) for p in table["payload"].to_pylist())
        return pa.table({"pid": table["pid"][:1], "payload": pa.array([one.to_bytes()])})

    if merge == "tree":
        rows = tree(rows, values.rdd.getNumPartitions(), together, fanout=fanout)
    parts = [RankSummary.from_bytes(bytes(r["payload"])) for r in rows.collect()]
    return (fold_left if merge == "driver" else tree_merge)(parts)


def summary(values: DataFrame, shares: Sequence[Fraction], eps: float, merge: str = "tree") -> list:
    s = merged_summary(values, eps, merge)
    return [] if s is None else [_back(s.query(int(q * s.n)), kind_of(values)) for q in shares]


def kll(values: DataFrame, shares: Sequence[Fraction], eps: float, merge: str = "tree") -> list:
    """The randomised sketch built into Spark, merged by its aggregate."""
    kind = kind_of(values)
    k = min(65535, max(8, round(3 / eps)))
    sketch = _plain(values).agg(F.kll_sketch_agg_double(F.col("v").cast("double"), F.lit(k)).alias("s"))
    row = sketch.select(*[F.kll_sketch_get_quantile_double("s", F.lit(float(q))).alias(f"p{i}") for i, q in enumerate(shares)]).first()
    return [_back(x, kind) for x in row] if row[0] is not None else []


def sample(values: DataFrame, shares: Sequence[Fraction], eps: float, merge: str = "tree") -> list:
    """Order statistics of a bounded row sample: for types that sketches do not take."""
    plain = _plain(values)
    n = plain.count()
    drawn = plain if n <= SAMPLE_ROWS else plain.sample(SAMPLE_ROWS / n, seed=11)
    got = sorted(r["v"] for r in drawn.limit(2 * SAMPLE_ROWS).collect())
    return [got[min(int(q * len(got)), len(got) - 1)] for q in shares] if got else []


def find(provider: str, values: DataFrame, shares: Sequence[Fraction], eps: float, merge: str = "tree") -> list:
    if provider not in PROVIDERS:
        raise ValueError(f"no pivot provider {provider!r}")
    if not supported(provider, kind_of(values)):
        provider = "sample"
    return globals()[provider](values, shares, eps, merge)
