"""Headline queries at one scale: one JSON line with seconds by query, counted costs beside.

The input of the method comparison is kept in its partitions, so that all methods read the same
values; each runs once to warm up and then REPEAT times. ``python bench.py --report`` prints the
comparison over partitions and distributions with 95 % intervals.
"""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

ROOT = str(Path(__file__).parent)
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"

from pyspark.sql import SparkSession  # noqa: E402

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
REPEAT = int(os.environ.get("BENCH_REPEAT", "3"))
HEADLINE = ["guided_p50_price", "guided_p99_price", "guided_edges_price", "guided_kernel_price", "guided_fused_price", "guided_refine_price", "guided_ties_quantity", "guided_treemerge_price", "guided_by_flag",
            "guided_join_delay", "sort_range_price", "prune_agg_price", "builtin_percentile_disc_price", "stock_native_bound", "join_asof_events", "win_moving_median", "agg_flags", "rank_all_events"]


def session() -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def seconds(run) -> float:
    began = time.perf_counter()
    run()
    return time.perf_counter() - began


def compare(spark: SparkSession, copies: int, parts: int, distribution: str, q: str, repeat: int = REPEAT, once: int = 1) -> dict:
    """Mean seconds with interval, and measured costs, of each method on the same values, kept in
    exactly ``parts`` partitions. Pruning runs ``once``."""
    from exactrank.plans.ledger import RunLedger, ci95
    from exactrank.plans.prune import prune_quantile
    from exactrank.quantile_queries import METHODS, kept_in
    from exactrank.sources.distributions import DISTRIBUTIONS, enlarged
    from exactrank.sources.shared import scratch

    path = scratch(spark, "bench")
    values = DISTRIBUTIONS[distribution](spark, SF)
    (enlarged(values, copies) if copies > 1 else values).write.parquet(path)
    df = kept_in(parts, spark.read.schema("v long").parquet(path))
    n, out = df.count(), {}
    methods = METHODS | {
        "native_sketch": lambda x, q, led: x.selectExpr(f"percentile_approx(v, {q}, 1000)").first(),
        "prune": lambda x, q, led: prune_quantile(x, "v", q, gather="agg", ledger=led),
    }
    try:
        for name, run in methods.items():
            times = once if name.startswith("prune") else repeat
            if times > 1:
                run(df, q, RunLedger())
            led = [RunLedger() for _ in range(times)]
            mean, low, high = ci95([seconds(lambda x=x: run(df, q, x)) for x in led])
            x = led[0]
            out[name] = {"seconds": round(mean, 3), "low": round(low, 3), "high": round(high, 3), "rounds": x.rounds, "full_shuffles": x.full_shuffles, "candidates": x.candidates, "rank_err": x.rank_err,
                         "net_rows": x.net_rows, "net_bytes": x.net_bytes, "driver_bytes": x.driver_bytes, "executor_seconds": round(x.executor_seconds, 2), "driver_seconds": round(x.driver_seconds, 3)}
    finally:
        df.unpersist()
    return {"n": n, "partitions": parts, "distribution": distribution, "q": q, "methods": out}


def main() -> None:
    spark = session()
    from exactrank import catalog

    if "--report" in sys.argv:
        for copies, parts, name, q in [(2, 12, "uniform", "0.5"), (17, 40, "uniform", "0.5"), (167, 40, "uniform", "0.5"), (167, 120, "uniform", "0.5"), *[(17, 40, d, q) for d in ("uniform", "zipf", "bimodal", "sorted") for q in ("0.5", "0.99")]]:
            print(json.dumps(compare(spark, copies, parts, name, q)), flush=True)
        return
    registered, times = catalog.queries(), {}
    registered[HEADLINE[0]](spark, SF).collect()  # starts the JVM's and Python's parts
    for name in HEADLINE:
        times[name] = round(min(seconds(lambda: registered[name](spark, SF).collect()) for _ in range(2)), 3)
    large = compare(spark, 50, 40, "uniform", "0.5", 2)
    for name, found in large["methods"].items():
        times[f"large_{name}"] = found["seconds"]
    rows = {"n": large["n"], "guided_values_per_second": round(large["n"] / large["methods"]["guided"]["seconds"])}
    speedup = round(large["methods"]["full_sort"]["seconds"] / large["methods"]["guided"]["seconds"], 2)
    print(json.dumps({"metric": "headline_seconds", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": SF, "large": rows, "guided_speedup_over_full_sort": speedup}))


if __name__ == "__main__":
    main()
