"""Count and discard: a random pivot splits the live interval, the side without the wanted rank goes.

The competing exact method: a logarithmic number of driver rounds. Messages (counts, one
uniform candidate for each side) are merged in a tree, collected, or made by one aggregate.
"""

from __future__ import annotations

import random
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark import StorageLevel, TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from exactrank.functions.kernels import Reservoir, three_way
from exactrank.functions.ranks import exact_share, target_rank
from exactrank.plans.guided import result_frame, sizes
from exactrank.plans.ledger import RunLedger
from exactrank.plans.treemerge import tree
from exactrank.plans.values import FLOATING, kind_of, literal, value_column

GATHERS, STORES = ("tree", "collect", "agg"), ("filter", "persist", "checkpoint")
#: Rounds after which lineage is cut by a checkpoint: a plan over kept intervals within kept
#: intervals doubles each round.
CUT_AFTER = {"persist": 4, "checkpoint": 1}


def _message_schema(kind: T.DataType) -> T.StructType:
    return T.StructType([T.StructField("pid", T.IntegerType()), *[T.StructField(c, T.LongType()) for c in ("below", "equal", "above")], T.StructField("lo", kind), T.StructField("hi", kind)])


def _messages(live: DataFrame, pivot, seed: int) -> DataFrame:
    kind = kind_of(live)

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pid = TaskContext.get().partitionId()
        rng = random.Random(seed * 1_000_003 + pid)
        low, high, equal, arrow = Reservoir(rng), Reservoir(rng), 0, None
        for b in batches:
            v = b["v"]
            arrow = v.type
            if pivot is None:
                high.add(v)
            else:
                below, e, above = three_way(v, pa.scalar(pivot, v.type))
                low.add(below)
                high.add(above)
                equal += e
        if arrow is not None:
            own = [pa.array([x], t) for x, t in ((pid, pa.int32()), (low.seen, pa.int64()), (equal, pa.int64()), (high.seen, pa.int64()))]
            own += [pa.array([None if r.value is None else r.value.as_py()], arrow) for r in (low, high)]
            yield pa.RecordBatch.from_arrays(own, ["pid", "below", "equal", "above", "lo", "hi"])

    return live.mapInArrow(local, _message_schema(kind))


def _joined(rows: list[dict], seed: int) -> dict:
    """Counts add up; a side's candidate survives with the probability of its side's size."""
    rng = random.Random(seed)
    out = {"below": 0, "equal": 0, "above": 0, "lo": None, "hi": None}
    for m in sorted(rows, key=lambda m: m["pid"]):
        for side, size in (("lo", "below"), ("hi", "above")):
            if m[size] and rng.randrange(out[size] + m[size]) < m[size]:
                out[side] = m[side]
            out[size] += m[size]
        out["equal"] += m["equal"]
    return out


def _gather(live: DataFrame, pivot, seed: int, how: str) -> dict:
    kind = kind_of(live)
    if how == "agg":
        v, at = F.col("v"), (literal(pivot, kind) if pivot is not None else None)
        below, equal, above = (v < at, v == at, v > at) if at is not None else (F.lit(False), F.lit(False), F.lit(True))
        draw = F.xxhash64("v", F.lit(seed))
        row = live.agg(
            F.count_if(below).alias("below"), F.count_if(equal).alias("equal"), F.count_if(above).alias("above"),
            F.max_by(F.when(below, v), F.when(below, draw)).alias("lo"), F.max_by(F.when(above, v), F.when(above, draw)).alias("hi"),
        ).first()
        return row.asDict()
    rows = _messages(live, pivot, seed)
    if how == "tree":
        schema = rows.schema

        def together(table: pa.Table) -> pa.Table:
            one = _joined(table.to_pylist(), seed) | {"pid": table["pid"][0].as_py()}
            return pa.Table.from_pylist([{f.name: one[f.name] for f in schema}], table.schema)

        rows = tree(rows, live.rdd.getNumPartitions(), together, fanout=8)
    return _joined([r.asDict() for r in rows.collect()], seed)


def select_rank(live: DataFrame, k: int, gather: str = "tree", store: str = "filter", seed: int = 1, max_rounds: int = 400, ledger: RunLedger | None = None) -> object:
    """The value of 0-based rank k of the column ``v``."""
    if gather not in GATHERS or store not in STORES:
        raise ValueError((gather, store))
    ledger = ledger if ledger is not None else RunLedger()
    spark, kind, base = live.sparkSession, kind_of(live), live
    kept: DataFrame | None = None
    bounds: dict[bool, Column] = {}  # by side, the tightest
    with ledger.round(spark, "first pivot"):
        pivot = _gather(live, None, seed, gather)["hi"]
    try:
        for turn in range(1, max_rounds + 1):
            with ledger.round(spark, "count"):
                m = _gather(live, pivot, seed * 7919 + turn, gather)
            if m["below"] <= k < m["below"] + m["equal"]:
                return pivot
            left = k < m["below"]
            at = literal(pivot, kind)
            bounds[left] = F.col("v") < at if left else F.col("v") > at
            if not left:
                k -= m["below"] + m["equal"]
            pivot = m["lo"] if left else m["hi"]
            if store == "filter":
                live = base
                for b in bounds.values():
                    live = live.where(b)
            else:
                live = live.where(bounds[left])
                if turn % CUT_AFTER[store] == 0:
                    live = live.checkpoint()
                live = live.persist(StorageLevel.MEMORY_AND_DISK)
                ledger.persists += 1
                if kept is not None:
                    live.count()
                    kept.unpersist()
                kept = live
        raise RuntimeError(f"rank not found in {max_rounds} rounds")
    finally:
        if kept is not None:
            kept.unpersist()


def is_computed(values: DataFrame) -> bool:
    """Whether the one column is more than a column of its source."""
    plan = values._jdf.queryExecution().optimizedPlan().toString()
    bare = r"\w+#\d+L?(?: AS v#\d+L?)?"
    return any(not re.search(rf"(?:Relation|LogicalRDD|LocalRelation|Filter|InMemoryRelation|Project \[{bare}\]$)", line) for line in plan.splitlines() if re.match(r"\W*[A-Z]", line))


def prune_quantile(df: DataFrame, col: str | Column, q, *, gather: str = "tree", store: str = "filter", rule: str = "nearest", seed: int = 1, max_rounds: int = 400, nan_policy: str = "last", ledger: RunLedger | None = None) -> DataFrame:
    """As ``guided_quantile``, by pruning. With ``store="filter"`` a computed column is made once
    and kept: bounds on it would else be pushed below, each with the whole expression in it."""
    ledger = ledger if ledger is not None else RunLedger()
    ledger.method = ledger.method or f"prune_{gather}"
    values = value_column(df, col, nan_policy)
    spark = df.sparkSession
    made = store == "filter" and is_computed(values)
    if made:
        values = values.persist(StorageLevel.MEMORY_AND_DISK)
        ledger.persists += 1
    if store in CUT_AFTER:
        from exactrank.sources.shared import ensure_checkpoint_dir

        ensure_checkpoint_dir(spark)
    try:
        with ledger.round(spark, "sizes"):
            n, nan, _, _ = sizes(values)
        ledger.n, ledger.partitions = n, values.rdd.getNumPartitions()
        live = values.where(~F.isnan("v")) if isinstance(kind_of(values), FLOATING) else values
        rows = []
        for x in q if isinstance(q, (list, tuple)) else [q]:
            t = target_rank(n, x, rule)
            if t is None:
                rows.append((float(exact_share(x)), None, None))
                continue
            got = [float("nan") if k >= n - nan else select_rank(live, k, gather, store, seed, max_rounds, ledger) for k in ([t.low, t.high] if t.weight else [t.low])]
            value = got[0] if len(got) == 1 else got[0] + (got[1] - got[0]) * float(t.weight)
            rows.append((float(exact_share(x)), t.low, float(value) if rule in ("midpoint", "linear") else value))
    finally:
        if made:
            values.unpersist()
    return result_frame(spark, rows, kind_of(values), rule in ("midpoint", "linear"))
