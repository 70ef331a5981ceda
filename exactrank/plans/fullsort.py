"""Exact quantiles by sorting everything: the baseline with one full shuffle."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from exactrank.functions.ranks import exact_share, target_rank
from exactrank.plans.guided import result_frame, sizes
from exactrank.plans.ledger import RunLedger
from exactrank.plans.values import kind_of, value_column

HOWS = ("range", "rdd", "global_limit")
#: Rows that the tasks of a top-k may send to the driver together.
TOPK_ROWS = 500_000


def _in_partitions(ordered: DataFrame) -> DataFrame:
    """Sorted values with their partition and place in it, kept, because another run would sample
    other splitters."""
    return ordered.select("v", F.spark_partition_id().alias("pid"), F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1).alias("idx")).persist(StorageLevel.MEMORY_AND_DISK)


def _counted(ordered: DataFrame) -> list[tuple[int, int]]:
    return sorted(ordered.groupBy("pid").count().collect())


def _value_at(ordered: DataFrame, held: list[tuple[int, int]], k: int) -> object:
    for pid, c in held:
        if k < c:
            return ordered.where((F.col("pid") == pid) & (F.col("idx") == k)).first()["v"]
        k -= c


def sort_quantile(df: DataFrame, col: str | Column, q, *, how: str = "range", rule: str = "nearest", nan_policy: str = "last", partitions: int | None = None, ledger: RunLedger | None = None) -> DataFrame:
    """``range``: range partitioning on sampled splitters, sorted partitions, sizes, one lookup.
    ``rdd``: the same by the RDD interface. ``global_limit``: ORDER BY with OFFSET, which the
    optimizer turns into a top-k and which is therefore no full sort. A top-k holds all rows up
    to the rank in each task and in the driver, so it counts from the nearer end and is used
    while these are ``TOPK_ROWS`` at most; beyond, ORDER BY sorts once and the offset is shared
    out over its partitions."""
    if how not in HOWS:
        raise ValueError(f"no sort {how!r}")
    ledger = ledger if ledger is not None else RunLedger()
    ledger.method = ledger.method or f"sort_{how}"
    values, spark = value_column(df, col, nan_policy), df.sparkSession
    kind = kind_of(values)
    parts = partitions or values.rdd.getNumPartitions()
    shares = list(q) if isinstance(q, (list, tuple)) else [q]
    ledger.partitions = parts
    ordered, held, at = None, [], None
    if how == "range":
        ordered = _in_partitions(values.repartitionByRange(parts, "v").sortWithinPartitions("v"))
        ledger.persists += 1
        with ledger.round(spark, "sort"):
            held = _counted(ordered)
        n = sum(c for _, c in held)

        def at(k: int):
            return _value_at(ordered, held, k)
    elif how == "rdd":
        numbered = values.rdd.map(lambda r: r[0]).sortBy(lambda v: v, numPartitions=parts).zipWithIndex().map(lambda p: (p[1], p[0]))
        with ledger.round(spark, "sort"):
            n = numbered.count()

        def at(k: int):
            return numbered.filter(lambda p: p[0] == k).first()[1]
    else:
        with ledger.round(spark, "sizes"):
            n = sizes(values)[0]

        def at(k: int):
            nonlocal ordered, held
            before = min(k, n - 1 - k)
            if (before + 1) * parts <= TOPK_ROWS:
                return values.orderBy("v" if before == k else F.desc("v")).offset(before).limit(1).first()["v"]
            if ordered is None:
                ordered = _in_partitions(values.orderBy("v"))
                ledger.persists += 1
                held = _counted(ordered)
            return _value_at(ordered, held, k)
    ledger.n = n
    rows = []
    try:
        for x in shares:
            t = target_rank(n, x, rule)
            if t is None:
                rows.append((float(exact_share(x)), None, None))
                continue
            with ledger.round(spark, "lookup"):
                value = at(t.low)
                if rule in ("midpoint", "linear"):
                    value = float(value) + (float(at(t.high)) - float(value)) * float(t.weight) if t.weight else float(value)
            rows.append((float(exact_share(x)), t.low, value))
    finally:
        if ordered is not None:
            ordered.unpersist()
    return result_frame(spark, rows, kind, rule in ("midpoint", "linear"))
