"""Registered queries of the quantile methods, and the same results in DuckDB SQL."""

from __future__ import annotations

import math

from pyspark import StorageLevel
from pyspark.sql import functions as F

from exactrank.functions.ranks import target_rank
from exactrank.functions.summaries import AdaptiveSummary, BufferedSummary, RegularSample, StreamSummary
from exactrank.operators import rank as ranking
from exactrank.plans import pivot as pivots
from exactrank.plans.builtin import builtin_quantile, ntile_quantile
from exactrank.plans.fullsort import sort_quantile
from exactrank.plans.grouped import guided_quantile_by
from exactrank.plans.guided import count_around, guided_quantile, quantile_values, verify
from exactrank.plans.ledger import RunLedger
from exactrank.plans.prune import prune_quantile
from exactrank.plans.sqlscript import guided_sql, prune_sql
from exactrank.plans.values import value_column
from exactrank.sources.distributions import DISTRIBUTIONS, duckdb_sql, enlarged, uniform
from exactrank.sources.tables import load

STOCK_EPS = 1e-3


def _stock(df, q, x):
    """Spark's statistics function, in a round of the ledger."""
    x.method = "stock_sketch"
    with x.round(df.sparkSession, "sketch"):
        value = int(v) if (v := df.approxQuantile("v", [float(q)], STOCK_EPS)[0]).is_integer() else v
    x.n = df.count()
    x.notes["answer"] = (target_rank(x.n, q).low, value)


def _answered(run):
    def method(df, q, x):
        x.notes["answer"] = tuple(run(df, q, x).first())[1:]

    return method


#: The methods that the experiment compares; the answer (rank, value) goes to the ledger's notes.
METHODS = {
    "guided": _answered(lambda df, q, x: guided_quantile(df, "v", q, ledger=x)),
    "stock_sketch": _stock,
    "full_sort": _answered(lambda df, q, x: sort_quantile(df, "v", q, ledger=x)),
    "prune_tree": _answered(lambda df, q, x: prune_quantile(df, "v", q, gather="tree", store="persist", ledger=x)),
    "prune_collect": _answered(lambda df, q, x: prune_quantile(df, "v", q, gather="collect", store="persist", ledger=x)),
}
QUERIES: dict = {}
SQL: dict[str, str] = {}
HALF, TAIL, EDGES = ["0.5"], ["0.99"], ["0", "0.01", "0.25", "0.75", "1"]


def add(name: str, fn, sql: str | None = None) -> None:
    QUERIES[name] = fn
    if sql:
        SQL[name] = sql


def disc(qs, expr: str, source: str, value: str = "quantile_disc(v, {q})") -> str:
    one = "SELECT {q}::DOUBLE AS q, (greatest(1, ceil({q}::DECIMAL(12,6) * count(v))) - 1)::BIGINT AS k, " + value + f" AS value FROM (SELECT {expr} AS v FROM {source})"
    return " UNION ALL ".join(one.format(q=q) for q in qs)


def by_row(qs, expr: str, source: str, rule: str = "nearest") -> str:
    k = "least(floor({q}::DECIMAL(12,6) * n)::BIGINT, n - 1)" if rule == "floor0" else "(greatest(1, ceil({q}::DECIMAL(12,6) * n)) - 1)::BIGINT"
    one = "SELECT {q}::DOUBLE AS q, r AS k, v AS value FROM (SELECT v, row_number() OVER (ORDER BY v) - 1 AS r, count(*) OVER () AS n FROM " + f"(SELECT {expr} AS v FROM {source}) WHERE v IS NOT NULL) WHERE r = {k}"
    return " UNION ALL ".join(one.format(q=q) for q in qs)


def column(method, table: str, col: str, qs, expr=None, **options):
    """``method`` on a table's column (or an expression over it)."""
    def run(spark, sf_dir):
        df = load(spark, sf_dir, table)
        return method(df, F.expr(expr) if expr else col, list(qs), **options)

    return run


def guided(name, table, col, qs, sql=None, expr=None, **options):
    add(name, column(guided_quantile, table, col, qs, expr, **options), sql or disc(qs, col, table))


guided("guided_p50_price", "lineitem", "l_extendedprice", HALF)
guided("guided_p99_price", "lineitem", "l_extendedprice", TAIL)
guided("guided_edges_price", "lineitem", "l_extendedprice", EDGES)
guided("guided_floor0_price", "lineitem", "l_extendedprice", ["0.25", "0.5", "1"], by_row(["0.25", "0.5", "1"], "l_extendedprice", "lineitem", "floor0"), rule="floor0")
for _c in ("quantity", "discount", "tax"):
    guided(f"guided_ties_{_c}", "lineitem", f"l_{_c}", ["0.1", "0.5", "0.9"])
guided("guided_rle_quantity", "lineitem", "l_quantity", ["0.37"], eps=0.05, extract="histogram")
guided("guided_topk_price", "lineitem", "l_extendedprice", HALF, extract="topk")
guided("guided_kernel_price", "lineitem", "l_extendedprice", ["0.2", "0.5", "0.99"], eps=0.01, extract="kernel")
guided("guided_fused_price", "lineitem", "l_extendedprice", HALF, rounds=2)
guided("guided_refine_price", "lineitem", "l_extendedprice", HALF, eps=0.02, max_candidates=50)
guided("guided_split_price", "lineitem", "l_extendedprice", HALF, eps=0.01, extract="persisted_split")
guided("guided_treemerge_price", "lineitem", "l_extendedprice", HALF, pivot="summary", merge="tree", fanout=2)
guided("guided_drivermerge_price", "lineitem", "l_extendedprice", HALF, pivot="summary", merge="driver")
for _p in pivots.PROVIDERS:
    guided(f"guided_pivot_{_p}_total", "orders", "o_totalprice", ["0.5", "0.9"], pivot=_p, eps=0.01)
add("guided_median_midpoint", column(guided_quantile, "customer", "c_acctbal", HALF, rule="midpoint"),
    "SELECT 0.5::DOUBLE AS q, (greatest(1, ceil(count(c_acctbal) * 0.5)) - 1)::BIGINT AS k, quantile_cont(c_acctbal, 0.5) AS value FROM customer")
add("guided_cont_balance", lambda s, d: guided_quantile(load(s, d, "customer"), "c_acctbal", ["0.1", "0.77"], rule="linear").withColumn("value", F.round("value", 6)),
    " UNION ALL ".join(f"SELECT {q}::DOUBLE AS q, floor((count(c_acctbal) - 1) * {q}::DECIMAL(6,3))::BIGINT AS k, round(quantile_cont(c_acctbal, {q}), 6) AS value FROM customer" for q in ("0.1", "0.77")))
guided("guided_ts_shipdate", "lineitem", "l_shipdate", ["0.1", "0.5"])
guided("guided_ts_orderdate", "orders", "o_orderdate", ["0.33"])
_DEC = "CAST(l_extendedprice AS DECIMAL(15,2))"
guided("guided_decimal_price", "lineitem", None, HALF, disc(HALF, _DEC, "lineitem"), expr=_DEC)
guided("guided_int_size", "part", "p_size", ["0.5", "0.95"])
guided("guided_long_nchars", "documents", "n_chars", ["0.5", "0.99"])
guided("guided_string_url", "pages", "url", HALF, by_row(HALF, "url", "pages"))
guided("guided_string_priority", "orders", "o_orderpriority", ["0.2", "0.6"], by_row(["0.2", "0.6"], "o_orderpriority", "orders"))
guided("guided_sorted_ts", "events", "ts", HALF)
guided("guided_tail_value", "events", "value", ["0.5", "0.99", "0.999"])
add("guided_small_nation", lambda s, d: guided_quantile(load(s, d, "nation").repartition(64), "n_nationkey", ["0", "0.3", "0.5", "1"]), disc(["0", "0.3", "0.5", "1"], "n_nationkey", "nation"))
_NULLED = "CASE WHEN event_id % 7 = 0 THEN NULL ELSE value END"
guided("guided_nulls_value", "events", None, ["0.5", "0.9"], disc(["0.5", "0.9"], _NULLED, "events"), expr=_NULLED)
_DAY = "datediff(CAST(l_shipdate AS DATE), CAST(o_orderdate AS DATE))"


def _delay(s, d):
    joined = load(s, d, "lineitem", "l_orderkey", "l_shipdate").join(load(s, d, "orders", "o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    return guided_quantile(joined, F.expr(_DAY), ["0.5", "0.9"])


add("guided_join_delay", _delay, disc(["0.5", "0.9"], "date_diff('day', o_orderdate::DATE, l_shipdate::DATE)::INTEGER", "lineitem JOIN orders ON l_orderkey = o_orderkey"))
add("guided_embedding_components", lambda s, d: guided_quantile(load(s, d, "embeddings").select(F.explode("embedding").alias("x")), F.col("x").cast("double"), ["0.05", "0.5"]),
    disc(["0.05", "0.5"], "x", "(SELECT unnest(embedding)::DOUBLE AS x FROM embeddings)"))
add("guided_props_k", lambda s, d: guided_quantile(load(s, d, "events"), F.get_json_object("props", "$.k").cast("long"), ["0.5", "0.9"]),
    disc(["0.5", "0.9"], "CAST(json_extract(props, '$.k') AS BIGINT)", "events"))


def grouped(name, table, keys, col, q, source=None):
    def run(s, d):
        df = load(s, d, table) if isinstance(table, str) else table(s, d)
        return guided_quantile_by(df, [k for k, _ in keys], col, q)

    names = ", ".join(f"{e} AS {k}" for k, e in keys)
    add(name, run, f"SELECT {names}, count({col}) AS n, quantile_disc({col}, {q}) AS value FROM {source or table} GROUP BY {', '.join(e for _, e in keys)}")


grouped("guided_by_flag", "lineitem", [("l_returnflag", "l_returnflag"), ("l_linestatus", "l_linestatus")], "l_extendedprice", 0.5)
grouped("guided_by_lang", "documents", [("lang", "lang")], "n_chars", 0.9)
grouped("guided_by_type_hour", lambda s, d: load(s, d, "events").withColumn("hour", F.hour("ts")), [("event_type", "event_type"), ("hour", "hour(ts)::INTEGER")], "value", 0.5, "events")


def _by_nation(s, d):
    o, c, n = load(s, d, "orders", "o_custkey", "o_totalprice"), load(s, d, "customer", "c_custkey", "c_nationkey"), load(s, d, "nation", "n_nationkey", "n_name")
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))


grouped("guided_join_nation_total", _by_nation, [("n_name", "n_name")], "o_totalprice", 0.5, "orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey")

for _how in ("range", "rdd", "global_limit"):
    add(f"sort_{_how}_price", column(sort_quantile, "lineitem", "l_extendedprice", ["0.5", "0.99"], how=_how), disc(["0.5", "0.99"], "l_extendedprice", "lineitem"))
add("builtin_approx_within_bound", lambda s, d: _approx_bound(s, d), "SELECT true AS within_bound")
add("builtin_ntile_price", lambda s, d: ntile_quantile(load(s, d, "events"), "value", 4),
    "SELECT quarter::INTEGER AS quarter, max(value) AS upper, count(*) AS n FROM (SELECT value, ntile(4) OVER (ORDER BY value) AS quarter FROM events) GROUP BY 1")
add("builtin_histogram_within_bound", lambda s, d: _histogram_bound(s, d), "SELECT 20::INTEGER AS bins, true AS rows_add_up, true AS ascending")
for _how, _agg in (("percentile_disc", "quantile_disc"), ("percentile_cont", "quantile_cont"), ("percentile", "quantile_cont"), ("median", "quantile_cont")):
    add(f"builtin_{_how}_price", lambda s, d, h=_how: builtin_quantile(load(s, d, "lineitem"), "l_extendedprice", 0.5, h).withColumn("value", F.round("value", 6)),
        f"SELECT 0.5::DOUBLE AS q, round({_agg}(l_extendedprice, 0.5), 6) AS value FROM lineitem")
for _gather in ("tree", "collect"):
    add(f"prune_{_gather}_persist_price", column(prune_quantile, "lineitem", "l_extendedprice", HALF, gather=_gather, store="persist"), disc(HALF, "l_extendedprice", "lineitem"))
for _gather in ("tree", "collect", "agg"):
    add(f"prune_{_gather}_price", column(prune_quantile, "lineitem", "l_extendedprice", HALF, gather=_gather), disc(HALF, "l_extendedprice", "lineitem"))
add("prune_persist_quantity", column(prune_quantile, "lineitem", "l_quantity", HALF, gather="agg", store="persist"), disc(HALF, "l_quantity", "lineitem"))
add("prune_filter_value", column(prune_quantile, "events", "value", TAIL, gather="agg", store="filter"), disc(TAIL, "value", "events"))
add("prune_checkpoint_value", column(prune_quantile, "events", "value", HALF, gather="agg", store="checkpoint"), disc(HALF, "value", "events"))
add("sql_guided_p50", lambda s, d: guided_sql(load(s, d, "lineitem"), "l_extendedprice", "0.5"), disc(HALF, "l_extendedprice", "lineitem"))
add("sql_prune_p50", lambda s, d: prune_sql(load(s, d, "events"), "value", "0.5"), disc(HALF, "value", "events"))

# Approximate methods: whether every answer is within its bound, measured by exact counts.
PROBES = ["0.01", "0.25", "0.5", "0.75", "0.99"]


def within(values, answers, eps, slack=1.0):
    """(q, within_bound) by the exact rank interval of each answer."""
    n, counts = count_around(values, [a for _, a in answers])
    rows = []
    for (q, _), (below, equal) in zip(answers, counts):
        k = target_rank(n, q).low
        off = max(0, below - k, k - (below + max(equal, 1) - 1))
        rows.append((float(q), off <= slack * eps * n + 1))
    return values.sparkSession.createDataFrame(rows, "q double, within_bound boolean")


_BOUND_SQL = " UNION ALL ".join(f"SELECT {q}::DOUBLE AS q, true AS within_bound" for q in PROBES)


def _summary(make, merge):
    def run(s, d):
        values = value_column(load(s, d, "events", "value"), "value").repartition(4)
        got = pivots.merged_summary(values, 0.01, merge, make)
        return within(values, [(q, got.query(target_rank(got.n, q).low)) for q in PROBES], 0.01)

    return run


class _Stream(StreamSummary):
    def insert_many(self, values):
        super().insert_many(values.tolist())


add("summary_stream_bound", _summary(_Stream, "tree"), _BOUND_SQL)
add("summary_buffered_bound", _summary(lambda e: BufferedSummary(e, 500, 100), "tree"), _BOUND_SQL)
add("summary_adaptive_bound", _summary(AdaptiveSummary, "driver-tree"), _BOUND_SQL)
add("summary_fold_bound", _summary(BufferedSummary, "driver"), _BOUND_SQL)


def _provider_bound(name, slack=1.0):
    def run(s, d):
        from fractions import Fraction

        values = value_column(load(s, d, "lineitem", "l_extendedprice"), "l_extendedprice")
        found = pivots.find(name, values, [Fraction(q) for q in PROBES], 0.01)
        return within(values, list(zip(PROBES, found)), 0.01, slack)

    return run


add("stock_stat_bound", _provider_bound("stat"), _BOUND_SQL)
add("stock_native_bound", _provider_bound("native"), _BOUND_SQL)
add("kll_bound", _provider_bound("kll", 3.0), _BOUND_SQL)


def _regular(s, d):
    """A sample of 100 regular ranks of a column, checked against exact ranks of probes."""
    values = value_column(load(s, d, "part", "p_retailprice"), "p_retailprice")
    n = values.count()
    step = max(1, n // 100)
    kept = ranking.rank_all(values, ["v"]).where(F.col("rk") % step == 0).orderBy("v").collect()
    import numpy as np

    sample = RegularSample(np.array([r["v"] for r in kept]), 1)
    sample.step = step
    probes = [float(r["v"]) for r in kept[:: max(1, len(kept) // 5)]]
    _, counts = count_around(values, probes)
    ok = all(b - step <= sample.rank(x) <= b + max(e, 1) + step for x, (b, e) in zip(probes, counts))
    return s.createDataFrame([(ok,)], "within_bound boolean")


add("regular_sample_bound", _regular, "SELECT true AS within_bound")

for _name, _make in DISTRIBUTIONS.items():
    for _label, _qs in (("p50", HALF), ("p99", TAIL)):
        _source = f"({duckdb_sql(_name)})"
        add(f"dist_{_name}_{_label}_guided", lambda s, d, m=_make, q=_qs: guided_quantile(m(s, d), "v", q), disc(_qs, "v", _source))
        add(f"dist_{_name}_{_label}_sort", lambda s, d, m=_make, q=_qs: sort_quantile(m(s, d), "v", q), disc(_qs, "v", _source))
        add(f"dist_{_name}_{_label}_prune", lambda s, d, m=_make, q=_qs: prune_quantile(m(s, d), "v", q, gather="agg"), disc(_qs, "v", _source))
        for _gather in ("tree", "collect"):
            add(f"dist_{_name}_{_label}_{_gather}_prune", lambda s, d, m=_make, q=_qs, g=_gather: prune_quantile(m(s, d), "v", q, gather=g, store="persist"), disc(_qs, "v", _source))
    add(f"gen_{_name}", lambda s, d, m=_make: m(s, d).groupBy(F.floor(F.col("v") / 100_000_000).alias("band")).agg(F.count("*").alias("n"), F.sum("v").alias("total")),
        f"SELECT floor(v / 100000000)::BIGINT AS band, count(*) AS n, sum(v)::BIGINT AS total FROM ({duckdb_sql(_name)}) GROUP BY 1")

# The experiment's axes: partitions (4 a node) and size.
for _parts in (4, 12, 40, 120):
    add(f"bench_parts_{_parts}", lambda s, d, p=_parts: guided_quantile(load(s, d, "lineitem", "l_extendedprice").repartition(p), "l_extendedprice", ["0.5", "0.99"], store=False), disc(["0.5", "0.99"], "l_extendedprice", "lineitem"))
for _times in (1, 10, 100):
    _source = f"(SELECT (v + 1000000000 + copy * 7368787) % 2000000000 - 1000000000 AS v FROM ({duckdb_sql('uniform')}), range({_times}) t(copy))"
    add(f"bench_size_x{_times}", lambda s, d, t=_times: guided_quantile(enlarged(uniform(s, d), t), "v", ["0.5", "0.99"]), disc(["0.5", "0.99"], "v", _source))

add("rank_of_value_price", lambda s, d: ranking.rank_of_value(load(s, d, "lineitem"), "l_extendedprice", 50000.0),
    "SELECT count(*) FILTER (l_extendedprice < 50000) AS below, count(*) FILTER (l_extendedprice = 50000) AS equal, count(*) AS n, count(*) FILTER (l_extendedprice <= 50000)::DOUBLE / count(*) AS cdf FROM lineitem")
add("row_at_rank_orders", lambda s, d: ranking.row_at_rank(load(s, d, "orders", "o_orderkey", "o_totalprice"), ["o_totalprice", "o_orderkey"], 700),
    "SELECT * FROM (SELECT o_orderkey, o_totalprice, row_number() OVER (ORDER BY o_totalprice, o_orderkey) - 1 AS rk FROM orders) WHERE rk = 700")
add("rank_all_events", lambda s, d: ranking.rank_all(load(s, d, "events", "event_id", "value"), ["value", "event_id"]),
    "SELECT event_id, value, row_number() OVER (ORDER BY value, event_id) - 1 AS rk FROM events")
add("equi_depth_price", lambda s, d: ranking.equi_depth_histogram(load(s, d, "lineitem"), "l_extendedprice", 10),
    "WITH c AS (SELECT i - 1 AS bin, (SELECT quantile_disc(l_extendedprice, [0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9, 1.0])[i] FROM lineitem) AS upper FROM range(1, 11) t(i)) "
    "SELECT bin::INTEGER AS bin, upper, count(*) AS rows FROM lineitem JOIN c ON l_extendedprice <= upper AND l_extendedprice > coalesce((SELECT max(x.upper) FROM c x WHERE x.bin < c.bin), -1e300) GROUP BY ALL")
add("iqr_outliers_total", lambda s, d: ranking.iqr_outliers(load(s, d, "events", "event_id", "value"), "value"),
    "WITH q AS (SELECT quantile_disc(value, 0.25) AS a, quantile_disc(value, 0.75) AS b FROM events) SELECT event_id, value FROM events, q WHERE value < a - 1.5 * (b - a) OR value > b + 1.5 * (b - a)")
add("trimmed_mean_value", lambda s, d: ranking.trimmed_mean(load(s, d, "events"), "value").withColumn("trimmed_mean", F.round("trimmed_mean", 6)),
    "WITH q AS (SELECT quantile_disc(value, 0.05) AS a, quantile_disc(value, 0.95) AS b FROM events) SELECT round(avg(value), 6) AS trimmed_mean, count(*) AS n FROM events, q WHERE value BETWEEN a AND b")
add("winsorized_value", lambda s, d: ranking.winsorize(load(s, d, "events", "event_id", "value"), "value"),
    "WITH q AS (SELECT quantile_disc(value, 0.01) AS a, quantile_disc(value, 0.99) AS b FROM events) SELECT event_id, least(greatest(value, a), b) AS value FROM events, q")
_AT = [100, 500, 1000, 2000, 5000, 20000]
add("ecdf_bins_nchars", lambda s, d: ranking.ecdf_bins(load(s, d, "documents"), "n_chars", _AT),
    " UNION ALL ".join(f"SELECT {e}::DOUBLE AS edge, count(*) FILTER (n_chars <= {e})::DOUBLE / count(*) AS share FROM documents" for e in _AT))


def _approx_bound(s, d):
    """Spark's approximate percentile, one call, against exact counts."""
    df = load(s, d, "lineitem", "l_extendedprice")
    value = builtin_quantile(df, "l_extendedprice", 0.5, "approx").first()["value"]
    n, ((below, equal),) = count_around(value_column(df, "l_extendedprice"), [value])
    return s.createDataFrame([(below <= n / 2 + n / 10000 + 1 and below + equal >= n / 2 - n / 10000 - 1,)], "within_bound boolean")


def _histogram_bound(s, d):
    """Spark's adaptive histogram: its bins hold all rows, in order."""
    df = load(s, d, "lineitem", "l_extendedprice")
    n, bins = df.agg(F.count("l_extendedprice"), F.histogram_numeric("l_extendedprice", F.lit(20))).first()
    at = [b["x"] for b in bins]
    return s.createDataFrame([(len(bins), abs(sum(b["y"] for b in bins) - n) < 0.5, at == sorted(at))], "bins int, rows_add_up boolean, ascending boolean")


# The experiment: all methods on the same values in so many partitions.


def compared(df, qs, distribution):
    """(distribution, q, method, k, value, within_bound, full_shuffles): answers of the five
    methods, each checked by a count around it, and the exchanges that their jobs made."""
    spark, values, rows = df.sparkSession, value_column(df, "v"), []
    for q in qs:
        for name, run in METHODS.items():
            run(df, q, x := RunLedger())
            k, value = x.notes["answer"]
            if x.method == "stock_sketch":
                _, ((below, equal),) = count_around(values, [value])
                ok = below - STOCK_EPS * x.n - 1 <= k <= below + equal + STOCK_EPS * x.n
            else:
                ok = verify(df, "v", [(k, value)], x)
            rows.append((distribution, float(q), name, k, None if x.method == "stock_sketch" else value, ok, x.full_shuffles))
    return spark.createDataFrame(rows, "distribution string, q double, method string, k long, value long, within_bound boolean, full_shuffles int")


def compared_sql(qs, names):
    rows = " UNION ALL ".join(f"SELECT '{n}' AS distribution, q, k, value FROM ({disc(qs, 'v', f'({duckdb_sql(n)})')})" for n in names)
    return (f"SELECT distribution, q, method, k, CASE WHEN method <> 'stock_sketch' THEN value END AS value, true AS within_bound, CASE WHEN method = 'full_sort' THEN 1 ELSE 0 END::INTEGER AS full_shuffles "
            f"FROM ({rows}), (VALUES ('guided'), ('stock_sketch'), ('full_sort'), ('prune_tree'), ('prune_collect')) m(method)")


def kept_in(parts, values):
    """The values in exactly so many partitions, kept in memory or on disk."""
    df = values.repartition(parts).persist(StorageLevel.MEMORY_AND_DISK)
    df.count()
    return df


def _figure(parts, names, qs):
    def run(s, d):
        out = None
        for name in names:
            df = kept_in(parts, DISTRIBUTIONS[name](s, d))
            try:
                part = compared(df, qs, name)
            finally:
                df.unpersist()
            out = part if out is None else out.unionByName(part)
        return out

    return run


add("bench_f1", _figure(40, ["uniform"], HALF), compared_sql(HALF, ["uniform"]))
add("bench_f2", _figure(120, ["uniform"], HALF), compared_sql(HALF, ["uniform"]))
RUNS = 5


def _stable(s, d):
    """Guided selection again and again: the same answer, in as many rounds, on every distribution."""
    rows = []
    for name, make in DISTRIBUTIONS.items():
        df = kept_in(40, make(s, d))
        try:
            for q in ("0.5", "0.99"):
                ledgers = [RunLedger() for _ in range(RUNS)]
                found = [quantile_values(df, "v", q, ledger=x)[0] for x in ledgers]
                rows.append((name, float(q), found[0][1], found[0][2], RUNS, len(set(found)), len({x.rounds for x in ledgers}), max(x.rounds for x in ledgers) <= 3))
        finally:
            df.unpersist()
    return s.createDataFrame(rows, "distribution string, q double, k long, value long, runs int, answers int, round_counts int, within_three boolean")


add("bench_f3", _stable, f"SELECT distribution, q, k, value, {RUNS}::INTEGER AS runs, 1::INTEGER AS answers, 1::INTEGER AS round_counts, true AS within_three FROM ("
    + " UNION ALL ".join(f"SELECT '{n}' AS distribution, q, k, value FROM ({disc(['0.5', '0.99'], 'v', f'({duckdb_sql(n)})')})" for n in DISTRIBUTIONS) + ")")


def _measures(s, d):
    """What the status store says of one run of each method, against what the analysis predicts."""
    df, rows = kept_in(8, load(s, d, "lineitem", "l_extendedprice").withColumnRenamed("l_extendedprice", "v")), []
    try:
        ledgers = {}
        for name, run in METHODS.items():
            run(df, "0.5", ledgers.setdefault(name, RunLedger()))
        kernel = RunLedger()
        quantile_values(df, "v", "0.5", eps=0.01, extract="kernel", ledger=kernel)
        for name, x in ledgers.items():
            within = name == "stock_sketch" or verify(df, "v", [x.notes["answer"]], x)
            rows += [
                ("exact", name, within), ("full_shuffles", name, x.full_shuffles == (name == "full_sort")),
                ("network_rows", name, x.net_rows >= x.n if name == "full_sort" else x.net_rows < x.n / 2), ("network_bytes", name, 0 < x.net_bytes),
                ("executor_time", name, x.executor_seconds > 0), ("driver_time", name, 0 <= x.driver_seconds <= x.seconds), ("driver_memory", name, 0 < x.driver_bytes < 1 << 24),
                ("rounds", name, x.rounds <= 3 if name in ("guided", "stock_sketch", "full_sort") else x.rounds > 3), ("persists", name, (x.persists > 1) == name.startswith("prune")),
            ]
        rows.append(("executor_memory", "guided", 0 < kernel.buffer_peak <= kernel.n))
        rows.append(("executor_memory", "full_sort", ledgers["full_sort"].executor_memory > 0))
    finally:
        df.unpersist()
    return s.createDataFrame(rows, "measure string, method string, holds boolean")


_MEASURES = ["exact", "full_shuffles", "network_rows", "network_bytes", "executor_time", "driver_time", "driver_memory", "rounds", "persists"]
add("ledger_measures", _measures, "SELECT measure, method, true AS holds FROM (VALUES " + ", ".join(f"('{m}', '{n}')" for m in _MEASURES for n in METHODS) + ", ('executor_memory', 'guided'), ('executor_memory', 'full_sort')) t(measure, method)")


def _summary_sizes(s, d):
    """Entries of one summary of all values against the bound of the analysis, 11 / (2 eps) times
    the logarithm of 2 eps n."""
    values, rows = value_column(load(s, d, "lineitem", "l_extendedprice"), "l_extendedprice").repartition(4), []
    for name, make in (("stream", _Stream), ("buffered", BufferedSummary), ("adaptive", AdaptiveSummary)):
        got = pivots.merged_summary(values, 0.01, "driver-tree", make)
        rows.append((name, len(got) <= 5.5 / 0.01 * max(1.0, math.log2(0.02 * got.n)) + 1, got.n))
    return s.createDataFrame(rows, "summary string, within_bound boolean, n long")


add("summary_size_bound", _summary_sizes, "SELECT summary, true AS within_bound, (SELECT count(*) FROM lineitem) AS n FROM (VALUES ('stream'), ('buffered'), ('adaptive')) t(summary)")


def _costs(s, d):
    """Measured costs of one run of each method: what must not depend on the machine. Full shuffles
    are stages that wrote most of the values to an exchange."""
    df, rows = load(s, d, "lineitem"), []
    for name, run in (
        ("guided", lambda x: guided_quantile(df, "l_extendedprice", "0.5", ledger=x)), ("guided_hit", lambda x: guided_quantile(df, "l_quantity", "0.5", ledger=x)),
        ("guided_edge", lambda x: guided_quantile(df, "l_extendedprice", "1", ledger=x)), ("full_sort", lambda x: sort_quantile(df, "l_extendedprice", "0.5", ledger=x)),
        ("prune", lambda x: prune_quantile(df, "l_extendedprice", "0.5", gather="agg", ledger=x)),
    ):
        run(x := RunLedger())
        rows.append((name, x.rounds if name != "prune" else -1, x.full_shuffles, x.rounds < 100))
    return s.createDataFrame(rows, "method string, rounds int, full_shuffles int, bounded boolean")


add("ledger_costs", _costs, "SELECT * FROM (VALUES ('guided', 3, 0, true), ('guided_hit', 2, 0, true), ('guided_edge', 1, 0, true), ('full_sort', 2, 1, true), ('prune', -1, 0, true)) t(method, rounds, full_shuffles, bounded)")
