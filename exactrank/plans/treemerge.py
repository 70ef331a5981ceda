"""Merging partitions' small results in a tree of bounded fan-out, on the executors.

A level groups ``fanout`` neighbours by number; no task and not the driver ever holds more than
that many messages, however many partitions there are.
"""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

FANOUT = 64


def tree(rows: DataFrame, parts: int, merge: Callable[[pa.Table], pa.Table], keys: tuple[str, ...] = (), fanout: int = FANOUT) -> DataFrame:
    """``rows`` have a column ``pid`` (0 to parts - 1) besides ``keys``; ``merge`` turns the rows of a
    group into fewer. One group for each key is left."""
    while parts > 1:
        parts = -(-parts // fanout)
        rows = rows.withColumn("pid", F.floor(F.col("pid") / fanout).cast("int"))
        rows = rows.groupBy(*keys, "pid").applyInArrow(merge, rows.schema)
    return rows
