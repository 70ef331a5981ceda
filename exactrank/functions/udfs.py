"""User-defined functions around summaries, for what has no built-in: Arrow batches throughout."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from exactrank.functions.kernels import quickselect
from exactrank.functions.summaries import BufferedSummary, RankSummary


def clamp(low: float, high: float):
    """A scalar function that moves values into [low, high]."""

    @pandas_udf(T.DoubleType())
    def run(v: pd.Series) -> pd.Series:
        return v.clip(low, high)

    return run


@pandas_udf(T.DoubleType())
def group_median(v: pd.Series) -> float:
    """Discrete median of a group by selection; for groups that fit in a task."""
    a = v.dropna().to_numpy()
    return float(quickselect(a, (len(a) + 1) // 2 - 1)) if len(a) else None


def summarise_groups(df: DataFrame, keys: list[str], col: str, eps: float) -> DataFrame:
    """(keys, payload): a serialised summary of each group. Groups come in Arrow tables; for hot
    groups summarise partitions and merge instead (``plans.pivot.merged_summary``)."""

    def run(table: pa.Table) -> pa.Table:
        s = BufferedSummary(eps)
        s.insert_many(table[col].drop_null().to_numpy())
        return table.slice(0, 1).select(keys).append_column("payload", pa.array([s.summary().to_bytes()]))

    schema = df.select(*keys).schema.add("payload", "binary")
    return df.select(*keys, col).groupBy(*keys).applyInArrow(run, schema)


@udtf(returnType=T.StructType([T.StructField("v", T.DoubleType()), T.StructField("rank_low", T.LongType()), T.StructField("rank_high", T.LongType())]))
class SummaryRows:
    """The tuples of a serialised summary with their rank bounds, as rows."""

    def eval(self, payload: bytes) -> Iterator[tuple]:
        s = RankSummary.from_bytes(bytes(payload))
        least = np.cumsum(s.g)
        yield from zip(s.v.tolist(), least.tolist(), (least + s.slack).tolist())


def width_bin(col: str | Column, low: float, high: float, bins: int) -> Column:
    return F.width_bucket(F.col(col) if isinstance(col, str) else col, F.lit(low), F.lit(high), F.lit(bins))
