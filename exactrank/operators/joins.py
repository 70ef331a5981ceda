"""Joins around order statistics: by equality, ranges, intervals, nearest time."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: A side that is broadcast on request may have this many rows.
BROADCAST_ROWS = 1_000_000


def dimension_join(facts: DataFrame, dimension: DataFrame, on: Column, how: str = "inner", max_rows: int = BROADCAST_ROWS) -> DataFrame:
    """The dimension is broadcast if a bounded count shows that it is small, else left to the planner."""
    small = dimension.limit(max_rows + 1).count() <= max_rows
    return facts.join(F.broadcast(dimension) if small else dimension, on, how)


def range_join(left: DataFrame, value: str, right: DataFrame, lo: str, hi: str, width: int) -> DataFrame:
    """Rows of ``right`` whose [lo, hi) holds the value: equality on bins of ``width``, then the
    bounds. The right side is repeated for each bin it touches."""
    bins = F.sequence(F.floor(F.col(lo) / width), F.floor((F.col(hi) - 1) / width))
    dealt = right.where(F.col(hi) > F.col(lo)).withColumn("_bin", F.explode(bins))
    joined = left.withColumn("_bin", F.floor(F.col(value) / width)).join(dealt, "_bin")
    return joined.where((F.col(value) >= F.col(lo)) & (F.col(value) < F.col(hi))).drop("_bin")


def asof_join(left: DataFrame, right: DataFrame, keys: Sequence[str], time: str, carry: Sequence[str]) -> DataFrame:
    """Each row of ``left`` with the latest row of ``right`` of its keys at or before its time: one
    sort of both sides together, no row pairs. Equal times count as before."""
    payload = F.struct(F.col(time).alias("at"), *carry)
    marked = left.withColumn("_side", F.lit(1)).withColumn("_p", F.lit(None).cast(right.select(payload.alias("p")).schema["p"].dataType))
    other = right.select(*keys, time, payload.alias("_p")).withColumn("_side", F.lit(0))
    both = marked.unionByName(other, allowMissingColumns=True)
    w = Window.partitionBy(*keys).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    out = both.withColumn("_p", F.last("_p", ignorenulls=True).over(w)).where("_side = 1").drop("_side")
    return out.select(*left.columns, F.col("_p.at").alias(f"matched_{time}"), *[F.col(f"_p.{c}").alias(f"matched_{c}") for c in carry])


def interval_join(left: DataFrame, right: DataFrame, keys: Sequence[str], left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of equal keys where the right time is within ``seconds`` after the left one (both ends
    in). Rows meet in time slots of that width; a left row looks into two."""
    slot = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / seconds)
    a = left.withColumn("_slot", F.explode(F.array(slot(left_time), slot(left_time) + 1)))
    b = right.withColumn("_slot", slot(right_time))
    near = (F.col(right_time) >= F.col(left_time)) & (F.col(right_time) <= F.col(left_time) + F.make_dt_interval(secs=F.lit(seconds)))
    return a.join(b, [*keys, "_slot"]).where(near).drop("_slot")


def top_per_row(outer: DataFrame, inner: DataFrame, on: Column, order: Sequence[Column], n: int = 1) -> DataFrame:
    """For each outer row its first n inner rows (a lateral top-n)."""
    return outer.lateralJoin(inner.where(on).orderBy(*order).limit(n))


def salted_join(big: DataFrame, other: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """A join on a key that a few values dominate: the big side's rows are spread over ``salts``
    parts, the other side's repeated for each. For outer sizes AQE cannot split."""
    left = big.withColumn("_salt", F.pmod(F.xxhash64(*big.columns), F.lit(salts)).cast("int"))
    right = other.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return left.join(right, [key, "_salt"]).drop("_salt")
