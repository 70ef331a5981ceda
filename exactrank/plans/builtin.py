"""What a Spark user would write without this package."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

HOWS = {
    "percentile_disc": lambda c, q: f"percentile_disc({q}) WITHIN GROUP (ORDER BY {c})",
    "percentile_cont": lambda c, q: f"percentile_cont({q}) WITHIN GROUP (ORDER BY {c})",
    "percentile": lambda c, q: f"percentile({c}, {q})",
    "median": lambda c, q: f"median({c})",
    "approx": lambda c, q: f"percentile_approx({c}, {q}, 10000)",
}


def builtin_quantile(df: DataFrame, col: str, q: float, how: str = "percentile_disc") -> DataFrame:
    """(q, value). The exact ones merge a map of all distinct values in one task, and return
    doubles whatever the type."""
    if how == "median" and q != 0.5:
        raise ValueError("the median is the quantile 0.5")
    return df.select(F.lit(float(q)).alias("q"), F.col(col)).groupBy("q").agg(F.expr(HOWS[how](col, q)).alias("value"))


def ntile_quantile(df: DataFrame, col: str, tiles: int) -> DataFrame:
    """(quarter, upper, n) by Spark's ntile over one global order: a window without partitions, so
    one task sorts everything. What guided selection is there to avoid."""
    tile = F.ntile(tiles).over(Window.orderBy(col))
    return df.where(F.col(col).isNotNull()).select(col, tile.alias("quarter")).groupBy("quarter").agg(F.max(col).alias("upper"), F.count("*").alias("n"))
