"""Registered queries of the operators around the methods, and the same results in DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from exactrank.functions import udfs
from exactrank.operators import joins, rank
from exactrank.sources import formats
from exactrank.sources.shared import scratch
from exactrank.sources.tables import SCHEMAS, load

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(fn):
        QUERIES[fn.__name__] = fn
        if sql:
            SQL[fn.__name__] = sql
        return fn

    return keep


# Sources and sinks


@query("SELECT l_returnflag, l_quantity FROM lineitem WHERE l_quantity > 45")
def scan_lineitem_cols(s, d):
    return load(s, d, "lineitem", "l_returnflag", "l_quantity").where("l_quantity > 45")


def _round_trip(kind, table="nation"):
    def run(s, d):
        path = scratch(s, f"{kind}-{table}")
        formats.write(load(s, d, table), kind, path)
        return formats.read(s, kind, path, SCHEMAS[table]).drop(formats.BAD)

    run.__name__ = f"scan_{kind}_roundtrip"
    return query(f"SELECT * FROM {table}")(run)


for _kind in formats.FORMATS:
    _round_trip(_kind)


@query("SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_returnflag <> 'N' GROUP BY 1")
def sink_partitioned_counts(s, d):
    path = scratch(s, "lineitem-by-flag")
    formats.write(load(s, d, "lineitem", "l_returnflag", "l_extendedprice"), "parquet", path, ["l_returnflag"], ["l_extendedprice"])
    return s.read.schema("l_extendedprice double, l_returnflag string").parquet(path).where("l_returnflag <> 'N'").groupBy("l_returnflag").agg(F.count("*").alias("n"))


# Projection and filters


@query("SELECT l_orderkey, l_linenumber, (l_extendedprice::DECIMAL(12,2) * (1 - l_discount::DECIMAL(4,2)) * (1 + l_tax::DECIMAL(4,2)))::DOUBLE AS charge, CASE WHEN l_quantity >= 25 THEN 'bulk' ELSE 'small' END AS kind FROM lineitem")
def proj_revenue(s, d):
    li = load(s, d, "lineitem")
    charge = F.expr("CAST(CAST(l_extendedprice AS DECIMAL(12,2)) * (1 - CAST(l_discount AS DECIMAL(4,2))) * (1 + CAST(l_tax AS DECIMAL(4,2))) AS DOUBLE)")
    return li.select("l_orderkey", "l_linenumber", charge.alias("charge"), F.when(F.col("l_quantity") >= 25, "bulk").otherwise("small").alias("kind"))


@query("SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice > 100000 AND o_totalprice < 120000 AND o_orderstatus IN ('O', 'F') AND o_orderpriority LIKE '1%'")
def filter_window(s, d):
    o = load(s, d, "orders")
    return o.where((F.col("o_totalprice") > 100000) & (F.col("o_totalprice") < 120000) & F.col("o_orderstatus").isin("O", "F") & F.col("o_orderpriority").like("1%")).select("o_orderkey", "o_totalprice")


@query("SELECT event_id FROM events WHERE (CASE WHEN event_id % 5 = 0 THEN NULL ELSE event_type END) IS NOT DISTINCT FROM NULL")
def filter_null_safe(s, d):
    kind = F.when(F.col("event_id") % 5 != 0, F.col("event_type"))
    return load(s, d, "events").where(kind.eqNullSafe(F.lit(None).cast("string"))).select("event_id")


# Joins


@query("SELECT n_name, count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY 1")
def join_broadcast_nation(s, d):
    li, su, na = load(s, d, "lineitem", "l_suppkey", "l_extendedprice"), load(s, d, "supplier", "s_suppkey", "s_nationkey"), load(s, d, "nation", "n_nationkey", "n_name")
    named = joins.dimension_join(su, na, F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name")
    return joins.dimension_join(li, named, F.col("l_suppkey") == F.col("s_suppkey")).groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


_DELAY_SQL = "SELECT o_orderpriority, avg(date_diff('day', o_orderdate::DATE, l_shipdate::DATE)) AS delay, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _delay(hint):
    def run(s, d):
        li, o = load(s, d, "lineitem", "l_orderkey", "l_shipdate"), load(s, d, "orders", "o_orderkey", "o_orderdate", "o_orderpriority")
        days = F.datediff(F.col("l_shipdate").cast("date"), F.col("o_orderdate").cast("date"))
        return li.join(o.hint(hint), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.avg(days).alias("delay"), F.count("*").alias("n"))

    return run


for _name, _hint in (("join_smj_delay", "merge"), ("join_shj_delay", "shuffle_hash")):
    QUERIES[_name], SQL[_name] = _delay(_hint), _DELAY_SQL


@query("SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi_labels(s, d):
    return load(s, d, "documents", "doc_id", "lang").join(load(s, d, "labels", "doc_id"), "doc_id", "left_semi")


@query("SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti_labels(s, d):
    return load(s, d, "documents", "doc_id", "lang").join(load(s, d, "labels", "doc_id"), "doc_id", "left_anti")


@query("SELECT c_custkey, count(o_orderkey) AS n, coalesce(round(sum(o_totalprice), 2), 0) AS total FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_left_custorders(s, d):
    totals = load(s, d, "orders", "o_custkey", "o_totalprice").groupBy("o_custkey").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))
    c = load(s, d, "customer", "c_custkey")
    return c.join(totals, c["c_custkey"] == totals["o_custkey"], "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("total", F.lit(0.0)).alias("total"))


@query("SELECT c_custkey, s_suppkey, coalesce(c_nationkey, s_nationkey) AS nation FROM (SELECT * FROM customer WHERE c_custkey <= 40) FULL JOIN (SELECT * FROM supplier WHERE s_suppkey > 3) ON c_custkey = s_suppkey")
def join_full_keys(s, d):
    c, u = load(s, d, "customer").where("c_custkey <= 40"), load(s, d, "supplier").where("s_suppkey > 3")
    return c.join(u, F.col("c_custkey") == F.col("s_suppkey"), "full_outer").select("c_custkey", "s_suppkey", F.coalesce("c_nationkey", "s_nationkey").alias("nation"))


@query("SELECT r_name, count(*) AS n FROM region JOIN nation ON n_nationkey % 5 > r_regionkey GROUP BY 1")
def join_theta_small(s, d):
    return load(s, d, "region").join(F.broadcast(load(s, d, "nation")), F.col("n_nationkey") % 5 > F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"))


@query("SELECT band, count(*) AS n FROM orders JOIN (VALUES ('low', 0, 50000), ('mid', 50000, 200000), ('high', 200000, 1000000)) t(band, lo, hi) ON o_totalprice >= lo AND o_totalprice < hi GROUP BY 1")
def join_range_bins(s, d):
    bands = s.createDataFrame([("low", 0, 50000), ("mid", 50000, 200000), ("high", 200000, 1000000)], "band string, lo long, hi long")
    return joins.range_join(load(s, d, "orders", "o_totalprice"), "o_totalprice", F.broadcast(bands), "lo", "hi", 50000).groupBy("band").agg(F.count("*").alias("n"))


@query("SELECT p.event_id, p.user_id, v.ts AS matched_ts, v.value AS matched_value FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts")
def join_asof_events(s, d):
    e = load(s, d, "events", "event_id", "ts", "user_id", "event_type", "value")
    out = joins.asof_join(e.where("event_type = 'purchase'"), e.where("event_type = 'view'"), ["user_id"], "ts", ["value"])
    return out.select("event_id", "user_id", "matched_ts", "matched_value")


@query("SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def join_interval_events(s, d):
    e = load(s, d, "events", "event_id", "ts", "user_id", "event_type")
    a = e.where("event_type = 'click'").select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("a_ts"))
    b = e.where("event_type = 'purchase'").select(F.col("event_id").alias("second_id"), "user_id", F.col("ts").alias("b_ts"))
    return joins.interval_join(a, b, ["user_id"], "a_ts", "b_ts", 6 * 3600).select("first_id", "second_id")


@query("SELECT n_name, c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 1)")
def join_lateral_top1(s, d):
    n, c = load(s, d, "nation", "n_nationkey", "n_name"), load(s, d, "customer", "c_custkey", "c_nationkey", "c_acctbal")
    return joins.top_per_row(n, c, F.col("c_nationkey") == F.col("n_nationkey").outer(), [F.desc("c_acctbal"), F.asc("c_custkey")]).select("n_name", "c_custkey")


@query("SELECT event_type, count(*) AS n, sum(w) AS w FROM events JOIN (SELECT event_type AS t, count(*) AS w FROM events GROUP BY 1) ON event_type = t GROUP BY 1")
def join_salted_types(s, d):
    e = load(s, d, "events", "event_id", "event_type")
    weights = e.groupBy("event_type").agg(F.count("*").alias("w"))
    return joins.salted_join(e, weights, "event_type", 8).groupBy("event_type").agg(F.count("*").alias("n"), F.sum("w").alias("w"))


# Aggregates

_FLAGS = "l_returnflag, l_linestatus"


@query(f"SELECT {_FLAGS}, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_extendedprice), 4) AS price, max(l_tax) AS tax FROM lineitem GROUP BY 1, 2")
def agg_flags(s, d):
    return load(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.max("l_tax").alias("tax"))


@query("SELECT o_orderpriority, min(o_orderstatus) AS first_status, max(o_orderstatus) AS last_status FROM orders GROUP BY 1")
def agg_sort_path(s, d):
    """Strings as aggregation buffers: Spark sorts instead of hashing."""
    return load(s, d, "orders").groupBy("o_orderpriority").agg(F.min("o_orderstatus").alias("first_status"), F.max("o_orderstatus").alias("last_status"))


@query("SELECT p_brand, count(DISTINCT p_type) AS types, count(DISTINCT p_size) AS sizes FROM part GROUP BY 1")
def agg_distinct_parts(s, d):
    return load(s, d, "part").groupBy("p_brand").agg(F.count_distinct("p_type").alias("types"), F.count_distinct("p_size").alias("sizes"))


def _multi(kind):
    def run(s, d):
        li = load(s, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity")
        if kind == "gsets":
            g = li.groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus")
        else:
            g = getattr(li, kind)("l_returnflag", "l_linestatus")
        return g.agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("gid"))

    return run


for _kind, _clause in (("cube", f"CUBE ({_FLAGS})"), ("rollup", f"ROLLUP ({_FLAGS})"), ("gsets", "GROUPING SETS ((l_returnflag), (l_linestatus), ())")):
    QUERIES[f"agg_{_kind}_flags"] = _multi(_kind)
    SQL[f"agg_{_kind}_flags"] = f"SELECT {_FLAGS}, count(*) AS n, grouping_id({_FLAGS})::BIGINT AS gid FROM lineitem GROUP BY {_clause}"


@query("SELECT event_type, min(value) AS low, max(value) AS high, arg_max(event_id, value) AS top_id, arg_min(event_id, value) AS bottom_id, quantile_cont(value, 0.5) AS mid FROM events GROUP BY 1")
def agg_orderstats(s, d):
    # Of several events with the extreme value the first counts; ~x turns the order of ids around.
    known = F.col("value").isNotNull() & F.col("event_id").isNotNull()
    top, bottom = (F.when(known, F.struct("value", i.alias("i"))) for i in (F.bitwise_not("event_id"), F.col("event_id")))
    return load(s, d, "events").groupBy("event_type").agg(F.min("value").alias("low"), F.max("value").alias("high"), F.max_by("event_id", top).alias("top_id"), F.min_by("event_id", bottom).alias("bottom_id"), F.median("value").alias("mid"))


@query("SELECT 'hll' AS sketch, true AS within_bound UNION ALL SELECT 'approx_count_distinct', true UNION ALL SELECT 'count_min', true")
def sketch_distinct_within_bound(s, d):
    li = load(s, d, "lineitem", "l_partkey")
    true = li.select("l_partkey").distinct().count()
    a, b = li.agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 14)), F.approx_count_distinct("l_partkey", 0.02)).first()
    events = load(s, d, "events", "event_type")
    true_counts = {r["event_type"]: r["count"] for r in events.groupBy("event_type").count().collect()}
    total = sum(true_counts.values())
    sketch = bytes(events.agg(F.count_min_sketch("event_type", F.lit(0.01), F.lit(0.95), F.lit(7))).first()[0])
    stored = s.sparkContext._jvm.org.apache.spark.util.sketch.CountMinSketch.readFrom(sketch)
    over = [stored.estimateCount(k) - c for k, c in true_counts.items()]
    low = min(over) >= 0 and max(over) <= 0.01 * total and stored.totalCount() == total
    rows = [("hll", abs(a - true) <= 0.05 * true), ("approx_count_distinct", abs(b - true) <= 0.1 * true), ("count_min", low)]
    return s.createDataFrame(rows, "sketch string, within_bound boolean")


@query("SELECT l_linestatus, count(*) FILTER (l_returnflag = 'A') AS A, count(*) FILTER (l_returnflag = 'N') AS N, count(*) FILTER (l_returnflag = 'R') AS R FROM lineitem GROUP BY 1")
def pivot_flags(s, d):
    return load(s, d, "lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count(F.lit(1)))


@query("SELECT l_returnflag AS l_returnflag_l_linestatus, count(*) FILTER (l_linestatus = 'F') AS F, count(*) FILTER (l_linestatus = 'O') AS O FROM lineitem GROUP BY 1")
def crosstab_flags(s, d):
    return load(s, d, "lineitem").crosstab("l_returnflag", "l_linestatus")


@query("SELECT s_suppkey, 'nation' AS item, s_nationkey::DOUBLE AS value FROM supplier UNION ALL SELECT s_suppkey, 'balance', s_acctbal FROM supplier")
def unpivot_supplier(s, d):
    su = load(s, d, "supplier").select("s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance"))
    return su.unpivot("s_suppkey", ["nation", "balance"], "item", "value")


# Windows


@query("SELECT event_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd FROM events WINDOW w AS (PARTITION BY event_type ORDER BY value, event_id)")
def win_rank_events(s, d):
    w = Window.partitionBy("event_type").orderBy("value", "event_id")
    cols = {"rn": F.row_number(), "rk": F.rank(), "dr": F.dense_rank(), "quarter": F.ntile(4)}
    out = load(s, d, "events").withColumns({k: f.over(w) for k, f in cols.items()})
    return out.select("event_id", *cols, F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


@query("SELECT o_orderkey, lag(o_totalprice) OVER w AS before, lead(o_totalprice) OVER w AS after, first_value(o_orderkey) OVER w AS first_key, nth_value(o_orderkey, 2) OVER w AS second_key FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def win_lag_orders(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return load(s, d, "orders").select("o_orderkey", F.lag("o_totalprice").over(w).alias("before"), F.lead("o_totalprice").over(w).alias("after"), F.first("o_orderkey").over(w).alias("first_key"), F.nth_value("o_orderkey", 2).over(w).alias("second_key"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN 6 PRECEDING AND CURRENT ROW), 6) AS total FROM events")
def win_rows_sum(s, d):
    w = Window.partitionBy("user_id").orderBy("ts").rowsBetween(-6, 0)
    return load(s, d, "events").select("event_id", F.round(F.sum("value").over(w), 6).alias("total"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range_sum(s, d):
    e = load(s, d, "events", "event_id", "user_id", "ts")
    e.createOrReplaceTempView("exactrank_events")
    return s.sql("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL '1' DAY PRECEDING AND CURRENT ROW) AS n FROM exactrank_events")


@query("SELECT event_id, quantile_cont(value, 0.5) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN 6 PRECEDING AND CURRENT ROW) AS moving_median FROM events")
def win_moving_median(s, d):
    return rank.moving_median(load(s, d, "events"), ["user_id"], "ts", "value", 7).select("event_id", "moving_median")


# Order, sets


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk_orders(s, d):
    return load(s, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25)


@query("SELECT event_id FROM (SELECT event_id, CASE WHEN event_id % 3 = 0 THEN NULL ELSE value END AS v FROM events) ORDER BY v ASC NULLS FIRST, event_id LIMIT 20 OFFSET 10")
def sort_nulls(s, d):
    v = F.when(F.col("event_id") % 3 != 0, F.col("value"))
    return load(s, d, "events").orderBy(v.asc_nulls_first(), "event_id").offset(10).limit(20).select("event_id")


def _sets(name, fn, clause):
    def run(s, d):
        a = load(s, d, "orders").select(F.col("o_custkey").alias("k"))
        b = load(s, d, "customer").where("c_acctbal > 0").select(F.col("c_custkey").alias("k"))
        return fn(a, b)

    QUERIES[name] = run
    SQL[name] = f"SELECT o_custkey AS k FROM orders {clause} SELECT c_custkey AS k FROM customer WHERE c_acctbal > 0"


_sets("set_union_all", lambda a, b: a.union(b), "UNION ALL")
_sets("set_union", lambda a, b: a.union(b).distinct(), "UNION")
_sets("set_union_by_name", lambda a, b: a.unionByName(b), "UNION ALL")
_sets("set_intersect", lambda a, b: a.intersect(b), "INTERSECT")
_sets("set_intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL")
_sets("set_except", lambda a, b: a.subtract(b), "EXCEPT")
_sets("set_except_all", lambda a, b: a.exceptAll(b), "EXCEPT ALL")


# Functions


@query("SELECT p_partkey, length(p_name) AS n, lower(p_brand) AS brand, substr(p_type, 1, 4) AS head, split_part(p_name, ' ', 1) AS word, regexp_extract(p_brand, '[0-9]+') AS num, concat_ws('-', p_brand, p_size) AS tag, levenshtein(p_brand, 'Brand#11') AS far, trim('  ' || p_name || ' ') AS name FROM part")
def fn_string_docs(s, d):
    return load(s, d, "part").select("p_partkey", F.length("p_name").alias("n"), F.lower("p_brand").alias("brand"), F.substring("p_type", 1, 4).alias("head"), F.split_part("p_name", F.lit(" "), F.lit(1)).alias("word"), F.regexp_extract("p_brand", "[0-9]+", 0).alias("num"),
                                      F.concat_ws("-", "p_brand", F.col("p_size").cast("string")).alias("tag"), F.levenshtein("p_brand", F.lit("Brand#11")).alias("far"), F.trim(F.concat(F.lit("  "), "p_name", F.lit(" "))).alias("name"))


@query("SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, date_trunc('month', o_orderdate)::DATE AS month_start, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INTEGER AS days, (o_orderdate::DATE + INTERVAL 7 DAY)::DATE AS week_on FROM orders")
def fn_date_ship(s, d):
    day = F.col("o_orderdate").cast("date")
    return load(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.trunc(day, "month").alias("month_start"), F.datediff(day, F.lit("1992-01-01").cast("date")).alias("days"), F.date_add(day, 7).alias("week_on"))


@query("SELECT o_orderkey, round(o_totalprice / 3, 2) AS third, floor(o_totalprice)::BIGINT AS fl, ceil(o_totalprice)::BIGINT AS ce, round(ln(o_totalprice), 6) AS ln, abs(-o_totalprice) AS ab, o_orderkey % 7 AS md, greatest(o_totalprice, 100000) AS gr, least(o_totalprice, 100000) AS le FROM orders")
def fn_math_price(s, d):
    p = F.col("o_totalprice")
    return load(s, d, "orders").select("o_orderkey", F.round(p / 3, 2).alias("third"), F.floor(p).alias("fl"), F.ceil(p).alias("ce"), F.round(F.log(p), 6).alias("ln"), F.abs(-p).alias("ab"), F.pmod("o_orderkey", F.lit(7)).alias("md"), F.greatest(p, F.lit(100000.0)).alias("gr"), F.least(p, F.lit(100000.0)).alias("le"))


@query("SELECT least(greatest(floor((value - 0) / 50) + 1, 0), 11)::BIGINT AS bin, count(*) AS n FROM events GROUP BY 1")
def fn_width_bins(s, d):
    return load(s, d, "events").groupBy(udfs.width_bin("value", 0.0, 500.0, 10).alias("bin")).agg(F.count("*").alias("n"))


@query("SELECT vec_id, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 5) AS norm, len(list_filter(embedding, lambda x: x > 0)) AS pos, list_sort(embedding)[1] AS low, embedding[3] AS third FROM embeddings")
def fn_array_emb(s, d):
    e = F.col("embedding")
    norm = F.aggregate(e, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    return load(s, d, "embeddings").select("vec_id", F.size(e).cast("long").alias("n"), F.round(norm, 5).alias("norm"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("pos"), F.array_sort(e)[0].alias("low"), F.element_at(e, 3).alias("third"))


@query("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, CAST(json_extract(props, '$.k') AS BIGINT) % 2 = 0 AS even FROM events")
def fn_json_props(s, d):
    k = F.from_json("props", "k long")["k"]
    return load(s, d, "events").select("event_id", k.alias("k"), (k % 2 == 0).alias("even"))


@query("SELECT event_id, least(greatest(value, 10), 200) AS value FROM events")
def udf_clamp(s, d):
    return load(s, d, "events").select("event_id", udfs.clamp(10.0, 200.0)("value").alias("value"))


@query("SELECT event_type, quantile_disc(value, 0.5) AS mid FROM events GROUP BY 1")
def udaf_group_median(s, d):
    return load(s, d, "events").groupBy("event_type").agg(udfs.group_median("value").alias("mid"))


@query("SELECT event_type, count(*) AS n, true AS ordered FROM events GROUP BY 1")
def udtf_summary_rows(s, d):
    """Summaries by type opened into rows: the last upper rank is the group's size."""
    udfs.summarise_groups(load(s, d, "events"), ["event_type"], "value", 0.01).createOrReplaceTempView("exactrank_summaries")
    s.udtf.register("summary_rows", udfs.SummaryRows)
    return s.sql("SELECT event_type, max(rank_high) AS n, bool_and(rank_low <= rank_high) AS ordered FROM exactrank_summaries, LATERAL summary_rows(payload) GROUP BY event_type")


@query("SELECT role, count(*) AS n, max(turn) AS last_turn FROM conversations WHERE text <> '' GROUP BY 1")
def agg_turns(s, d):
    return load(s, d, "conversations", "role", "turn", "text").where("text <> ''").groupBy("role").agg(F.count("*").alias("n"), F.max("turn").alias("last_turn"))


@query("SELECT event_id FROM events WHERE event_id * 2654435761 % 4294967296 < 429496730")
def sample_by_key(s, d):
    """A sample that depends on the key alone: the same rows at every partitioning."""
    return load(s, d, "events", "event_id").where(F.col("event_id") * 2654435761 % 4294967296 < 429496730)
