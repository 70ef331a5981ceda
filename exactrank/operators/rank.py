"""Ranks without a window over one partition, and what is built from quantiles."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from exactrank.plans.guided import count_around, quantile_values
from exactrank.plans.values import value_column
from exactrank.sources.shared import scratch


def rank_of_value(df: DataFrame, col: str, x) -> DataFrame:
    """(below, equal, n, cdf) of a value: one scan."""
    values = value_column(df, col)
    n, ((below, equal),) = count_around(values, [x])
    return df.sparkSession.createDataFrame([(below, equal, n, (below + equal) / n if n else None)], "below long, equal long, n long, cdf double")


def rank_all(df: DataFrame, order: Sequence[str], out: str = "rk", partitions: int | None = None) -> DataFrame:
    """``df`` with 0-based positions in the order: a range shuffle, positions within partitions,
    plus the sizes of those before (as many numbers as partitions)."""
    parts = partitions or max(1, df.rdd.getNumPartitions())
    ordered = df.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    numbered = ordered.withColumn("_pid", F.spark_partition_id()).withColumn("_idx", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1))
    # Stored, because another run would sample other splitters; a table needs no release.
    path, schema = scratch(df.sparkSession, "ranked"), numbered.schema
    numbered.write.parquet(path)
    numbered = df.sparkSession.read.schema(schema).parquet(path)
    before, starts = 0, []
    for pid, n in sorted(numbered.groupBy("_pid").count().collect()):
        starts.append((pid, before))
        before += n
    table = F.broadcast(df.sparkSession.createDataFrame(starts, "_pid int, _start long"))
    return numbered.join(table, "_pid").withColumn(out, F.col("_start") + F.col("_idx")).drop("_pid", "_idx", "_start")


def row_at_rank(df: DataFrame, order: Sequence[str], k: int) -> DataFrame:
    return rank_all(df, order).where(F.col("rk") == k)


def equi_depth_histogram(df: DataFrame, col: str, bins: int) -> DataFrame:
    """(bin, upper, rows): exact quantiles as bounds, all found in the same three rounds."""
    cuts = [v for *_, v in quantile_values(df, col, [f"{i}/{bins}" for i in range(1, bins + 1)])]
    b = F.lit(0)
    for i, c in enumerate(cuts[:-1]):
        b = F.when(F.col("v") > F.lit(c), i + 1).otherwise(b)
    table = df.sparkSession.createDataFrame(list(enumerate(cuts)), "bin int, upper double")
    return value_column(df, col).groupBy(b.cast("int").alias("bin")).agg(F.count("*").alias("rows")).join(F.broadcast(table), "bin").select("bin", "upper", "rows")


def iqr_outliers(df: DataFrame, col: str, factor: float = 1.5) -> DataFrame:
    """Rows outside the quartiles by more than ``factor`` times their distance."""
    (_, _, a), (_, _, b) = quantile_values(df, col, ["0.25", "0.75"])
    low, high = a - factor * (b - a), b + factor * (b - a)
    return df.where((F.col(col) < low) | (F.col(col) > high))


def trimmed_mean(df: DataFrame, col: str, share: str = "0.05") -> DataFrame:
    """Mean of the values from the quantile ``share`` to that of 1 - ``share``, both in."""
    from fractions import Fraction

    (_, _, a), (_, _, b) = quantile_values(df, col, [Fraction(share), 1 - Fraction(share)])
    return df.where(F.col(col).between(a, b)).agg(F.avg(col).alias("trimmed_mean"), F.count(col).alias("n"))


def winsorize(df: DataFrame, col: str, share: str = "0.01") -> DataFrame:
    """``df`` with the column's values moved in to those quantiles."""
    from fractions import Fraction

    (_, _, a), (_, _, b) = quantile_values(df, col, [Fraction(share), 1 - Fraction(share)])
    return df.withColumn(col, F.least(F.greatest(F.col(col), F.lit(a)), F.lit(b)))


def ecdf_bins(df: DataFrame, col: str, edges: Sequence[float]) -> DataFrame:
    """(edge, share of values at or below): one scan for all edges."""
    values = value_column(df, col)
    n, counts = count_around(values, list(edges))
    return df.sparkSession.createDataFrame([(float(e), (b + q) / n) for e, (b, q) in zip(edges, counts)], "edge double, share double")


def moving_median(df: DataFrame, keys: Sequence[str], order: str, col: str, rows: int) -> DataFrame:
    """Exact median of the last ``rows`` rows of each key."""
    w = Window.partitionBy(*keys).orderBy(order).rowsBetween(1 - rows, 0)
    return df.withColumn("moving_median", F.percentile(col, 0.5).over(w))
