"""Exact quantiles of every group, as one DataFrame plan.

Pivots and a far bound on both sides come from one aggregate with sketches; counts from a
second; only values between pivot and bound are ranked, by a window within the group. A
group whose bound does not reach its rank is ranked without one.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def guided_quantile_by(df: DataFrame, keys: Sequence[str], col: str | Column, q: float, eps: float = 1e-3) -> DataFrame:
    """(keys, n, value) with the discrete quantile (1-based rank ceil(q n)) of each group;
    null keys are a group, null values do not count."""
    rows = df.select(*keys, (F.col(col) if isinstance(col, str) else col).alias("v")).where("v IS NOT NULL")
    probs = [max(q - 2 * eps, 0.0), float(q), min(q + 2 * eps, 1.0)]
    sketched = rows.groupBy(*keys).agg(F.count("v").alias("n"), F.percentile_approx("v", probs, round(1 / eps)).alias("p"))
    bounds = sketched.select(*keys, "n", F.col("p")[0].alias("lo"), F.col("p")[1].alias("p"), F.col("p")[2].alias("hi"))
    rank = F.greatest(F.lit(1), F.ceil(F.lit(str(q)).cast("decimal(20,15)") * F.col("n")).cast("long"))

    def with_bounds(b: DataFrame, *extra: str) -> DataFrame:
        b = b.select(*[F.col(k).alias(f"_{k}") for k in keys], *extra)
        same = F.lit(True)
        for k in keys:
            same = same & F.col(k).eqNullSafe(F.col(f"_{k}"))
        return rows.join(b, same).drop(*[f"_{k}" for k in keys])

    v, p = F.col("v"), F.col("p")
    counted = (
        with_bounds(bounds.withColumn("r", rank), "n", "r", "lo", "p", "hi").groupBy(*keys, "n", "r", "lo", "p", "hi")
        .agg(F.count_if(v < p).alias("below"), F.count_if(v == p).alias("equal"), F.count_if(v < F.col("lo")).alias("under"), F.count_if(v <= F.col("hi")).alias("upto"))
    )
    hit = (F.col("r") > F.col("below")) & (F.col("r") <= F.col("below") + F.col("equal"))
    right = F.col("r") > F.col("below") + F.col("equal")
    decided = counted.withColumn("hit", hit).withColumn("right", right).withColumn("d", F.when(right, F.col("r") - F.col("below") - F.col("equal")).otherwise(F.col("below") - F.col("r") + 1))
    done = decided.where("hit").select(*keys, "n", F.col("p").alias("value"))
    reach_right, reach_left = F.col("upto") >= F.col("r"), F.col("under") < F.col("r")
    candidate = F.when(F.col("right"), (v > p) & (~reach_right | (v <= F.col("hi")))).otherwise((v < p) & (~reach_left | (v >= F.col("lo"))))
    near = with_bounds(decided.where("NOT hit"), "n", "r", "lo", "p", "hi", "right", "d", "upto", "under").where(candidate)
    up = Window.partitionBy(*keys).orderBy(F.when(F.col("right"), v).asc(), F.when(~F.col("right"), v).desc())
    repaired = near.withColumn("nth", F.row_number().over(up)).where(F.col("nth") == F.col("d")).select(*keys, "n", v.alias("value"))
    return done.unionByName(repaired)
