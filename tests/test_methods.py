"""All exact methods against sorted lists: types, ties, nulls, NaN, layouts, forced pivots, costs."""

import datetime as dt
import math
import random
from decimal import Decimal

import pytest
from pyspark.sql import functions as F

from exactrank.functions.ranks import target_rank
from exactrank.operators.rank import rank_all, rank_of_value
from exactrank.plans import guided as g
from exactrank.plans import pivot as pivots
from exactrank.plans.fullsort import sort_quantile
from exactrank.plans.grouped import guided_quantile_by
from exactrank.plans.guided import InputChanged, guided_quantile
from exactrank.plans.ledger import RunLedger, ledger_table
from exactrank.plans.prune import prune_quantile
from exactrank.plans.values import value_column
from exactrank.sources.tables import load

SF = "/root/testdata/sf0.001"
QS = ["0", "0.13", "0.5", "0.99", "1"]


def column(spark, values, kind, parts=3):
    return spark.createDataFrame([(v,) for v in values], f"v {kind}").repartition(parts)


def want(values, qs=QS, rule="nearest"):
    live = [v for v in values if v is not None]
    nan = [v for v in live if isinstance(v, float) and math.isnan(v)]
    ordered = sorted(v for v in live if not (isinstance(v, float) and math.isnan(v))) + nan
    return [ordered[target_rank(len(ordered), q, rule).low] for q in qs]


def got(df):
    return [r["value"] for r in sorted(df.collect(), key=lambda r: r["q"])]


def same(a, b):
    return all((isinstance(x, float) and math.isnan(x) and math.isnan(y)) or x == y for x, y in zip(a, b, strict=True))


rng = random.Random(4)
CASES = {
    "int": ([rng.randrange(-50, 50) for _ in range(300)], "int"),
    "big": ([2**53 + i for i in range(40)] + [-(2**63), 2**63 - 1], "long"),
    "double": ([rng.gauss(0, 1) for _ in range(300)] + [0.0, -0.0, float("inf"), float("-inf")], "double"),
    "nan": ([1.0, float("nan"), None, 3.0, -0.0, 0.0, float("nan"), 7.0], "double"),
    "nulls": ([None if i % 7 == 0 else i % 13 for i in range(200)], "int"),
    "equal": ([5] * 60, "long"), "two": ([1, 9], "int"), "one": ([3], "int"),
    "decimal": ([Decimal(i * i % 97) / 100 for i in range(150)], "decimal(20,4)"),
    "date": ([dt.date(2020, 1, 1) + dt.timedelta(days=i * 37 % 400) for i in range(120)], "date"),
    "ntz": ([dt.datetime(2021, 5, 1) + dt.timedelta(seconds=i * 7919 % 10007, microseconds=i) for i in range(120)], "timestamp_ntz"),
    "interval": ([dt.timedelta(seconds=i * 31 % 101) for i in range(80)], "interval day to second"),
    "string": ([f"k{i * 17 % 61}é" for i in range(150)], "string"),
}


@pytest.mark.parametrize("case", CASES)
def test_guided_selection_on_every_type(spark, case):
    values, kind = CASES[case]
    df = column(spark, values, kind)
    assert same(got(guided_quantile(df, "v", QS, eps=0.05)), want(values))
    assert guided_quantile(df, "v", "0.5").schema["value"].dataType == df.schema["v"].dataType


@pytest.mark.parametrize("options", [
    {"extract": "topk"}, {"extract": "kernel", "fanout": 2}, {"extract": "histogram"}, {"extract": "persisted_split"}, {"rounds": 2}, {"max_candidates": 3},
    {"pivot": "stat"}, {"pivot": "summary", "merge": "tree", "fanout": 2}, {"pivot": "summary", "merge": "driver"}, {"pivot": "kll"}, {"pivot": "sample"},
], ids=str)
def test_variants_agree(spark, options):
    for name in ("int", "double", "nan", "nulls", "equal"):
        values, kind = CASES[name]
        assert same(got(guided_quantile(column(spark, values, kind, 5), "v", QS, eps=0.1, **options)), want(values)), name


@pytest.mark.parametrize("layout", ["one", "skewed", "empty", "sorted"])
def test_layouts(spark, layout):
    values = [i * 7919 % 1009 for i in range(900)]
    df = column(spark, values, "long")
    df = {"one": lambda: df.coalesce(1), "skewed": lambda: df.repartition(4, F.col("v") > 100), "empty": lambda: df.repartition(40).where("v > -1").repartition(60, "v"),
          "sorted": lambda: df.repartitionByRange(6, "v").sortWithinPartitions("v")}[layout]()
    for q in ({}, {"extract": "kernel", "fanout": 3}):
        assert got(guided_quantile(df, "v", QS, eps=0.1, **q)) == want(values)
    assert got(sort_quantile(df, "v", QS)) == want(values)
    assert got(prune_quantile(df, "v", ["0.5"], gather="tree")) == want(values, ["0.5"])


@pytest.mark.parametrize("forced", [-10**6, 10**6, 0, 500.5, 1008])
def test_any_pivot_gives_the_exact_answer(spark, monkeypatch, forced):
    values = [float(i * 7919 % 1009) for i in range(900)]
    monkeypatch.setattr(pivots, "stat", lambda v, shares, eps, merge="tree": [float(forced)] * len(shares))
    assert got(guided_quantile(column(spark, values, "double"), "v", ["0.2", "0.8"], pivot="stat", eps=0.1)) == want(values, ["0.2", "0.8"])


def test_the_literal_gap_would_be_wrong_on_ties(spark):
    df = load(spark, SF.replace("0.001", "0.1"), "lineitem", "l_quantity")
    n, ((below, equal),) = g.count_around(value_column(df, "l_quantity"), [25.0])
    assert (below, equal, n // 2) == (288006, 12021, 300000)
    assert got(guided_quantile(df, "l_quantity", "0.5")) == [25.0]


@pytest.mark.parametrize("gather", ["tree", "collect", "agg"])
@pytest.mark.parametrize("store", ["filter", "persist", "checkpoint"])
def test_pruning(spark, gather, store):
    values, kind = CASES["nulls"]
    assert got(prune_quantile(column(spark, values, kind), "v", ["0.3", "0.9"], gather=gather, store=store)) == want(values, ["0.3", "0.9"])


def test_sorting(spark):
    for how in ("range", "rdd", "global_limit"):
        values, kind = CASES["double"]
        assert got(sort_quantile(column(spark, values, kind), "v", QS, how=how)) == want(values)


def test_a_top_k_is_bounded_and_the_rest_is_exact(spark, monkeypatch):
    from pyspark.sql.classic.dataframe import DataFrame

    taken, offset = [], DataFrame.offset
    monkeypatch.setattr("exactrank.plans.fullsort.TOPK_ROWS", 40, raising=False)
    monkeypatch.setattr(DataFrame, "offset", lambda self, n: taken.append(n) or offset(self, n))
    values = [float(i * 37 % 500) for i in range(500)] + [float("nan")] * 3 + [None]
    shares = ["0", "0.004", "0.3", "0.5", "0.99", "1"]
    assert str(got(sort_quantile(column(spark, values, "double"), "v", shares, how="global_limit", partitions=4))) == str(want(values, shares))
    assert taken and max(taken) < 10


def test_bounds_on_a_computed_column_are_not_pushed_into_it(spark, monkeypatch):
    from exactrank.plans import prune
    from exactrank.sources.distributions import bimodal

    plans, gather = [], prune._gather
    monkeypatch.setattr(prune, "_gather", lambda live, *a: plans.append(live.select("v")._jdf.queryExecution().optimizedPlan().toString()) or gather(live, *a))
    df = bimodal(spark, SF)
    assert got(prune_quantile(df, "v", "0.5", gather="agg")) == want([r["v"] for r in df.collect()], ["0.5"])
    scans = [p.split("InMemoryRelation")[0] for p in plans]
    assert len(plans) > 3 and not any("l_partkey" in s for s in scans)
    plans.clear()
    prune_quantile(load(spark, SF, "lineitem", "l_extendedprice"), "l_extendedprice", "0.5", gather="agg")
    assert not any("InMemoryRelation" in p for p in plans)


def test_rules_that_interpolate(spark):
    values = [1.0, 2.0, 4.0, 8.0]
    df = column(spark, values, "double")
    assert got(guided_quantile(df, "v", "0.5", rule="midpoint")) == [3.0]
    assert got(guided_quantile(df, "v", ["0.25", "0.9"], rule="linear")) == pytest.approx([1.75, 6.8])
    assert got(prune_quantile(df, "v", "0.5", rule="midpoint", gather="agg")) == [3.0]


def test_no_values_bad_types_and_policies(spark):
    for df in (column(spark, [], "double"), column(spark, [None, None], "int")):
        assert got(guided_quantile(df, "v", "0.5")) == [None]
        assert got(prune_quantile(df, "v", "0.5")) == [None] == got(sort_quantile(df, "v", "0.5"))
    nan = column(spark, [1.0, float("nan"), 2.0], "double")
    assert got(guided_quantile(nan, "v", "1", nan_policy="drop")) == [2.0]
    with pytest.raises(ValueError):
        guided_quantile(nan, "v", "0.5", nan_policy="error")
    with pytest.raises(TypeError):
        guided_quantile(spark.createDataFrame([(True,)], "v boolean"), "v", "0.5")


def test_a_changed_input_is_noticed(spark, monkeypatch):
    df = column(spark, [float(i) for i in range(100)], "double")
    real = g.count_around
    monkeypatch.setattr(g, "count_around", lambda *a: (real(*a)[0] + 1, real(*a)[1]))
    with pytest.raises(InputChanged):
        guided_quantile(df, "v", "0.5", eps=0.1)


def test_counted_costs(spark):
    df = load(spark, SF.replace("0.001", "0.01"), "lineitem")
    x = RunLedger()
    guided_quantile(df, "l_extendedprice", "0.5", eps=0.01, ledger=x)
    assert (x.rounds, x.full_shuffles, x.persists) == (3, 0, 0) and 0 < x.rank_err <= 0.01 * x.n + 1
    x = RunLedger()
    guided_quantile(df, "l_quantity", "0.5", ledger=x)
    assert x.rounds == 2
    x = RunLedger()
    guided_quantile(df, "l_extendedprice", ["0", "1"], ledger=x)
    assert x.rounds == 1
    x = RunLedger()
    prune_quantile(df, "l_extendedprice", "0.5", gather="agg", ledger=x)
    assert 3 < x.rounds <= 6 * math.log(60000) + 10
    y = RunLedger()
    sort_quantile(df, "l_extendedprice", "0.5", ledger=y)
    assert y.full_shuffles == 1
    assert ledger_table(spark, {"a": x, "b": y}).count() == 2


def test_three_rounds_and_no_full_shuffle_at_1e8(spark):
    values = spark.range(10**8).selectExpr("id * 48271 % 2147483647 AS v")
    x = RunLedger()
    ((_, k, value),) = g.quantile_values(values, "v", "0.5", ledger=x)
    assert (x.rounds, x.full_shuffles, x.n) == (3, 0, 10**8) and x.net_rows < 10**6 and x.eps < g.COARSEST_EPS
    assert g.verify(values, "v", [(k, value)], x) and x.exact
    assert not g.verify(values, "v", [(k, value + 1000)], x) and x.exact is False


def test_an_added_shuffle_is_counted(spark):
    df = column(spark, [float(i) for i in range(5000)], "double", 8)
    for source, shuffles in ((df, 0), (df.repartition(5), 3)):
        x = RunLedger()
        g.quantile_values(source.cache() if not shuffles else source, "v", "0.3", eps=0.01, store=False, ledger=x)
        assert x.full_shuffles == shuffles, x.shuffled


def test_an_input_behind_an_exchange_is_made_once(spark):
    made = spark.sparkContext.accumulator(0)

    def counting(batches):
        for b in batches:
            made.add(b.num_rows)
            yield b

    df = spark.range(4000).mapInArrow(counting, "id long").repartition(6)
    assert got(guided_quantile(df, "id", ["0.5", "0.9"], eps=0.05)) == [1999, 3599]
    assert made.value == 4000
    assert g.stored_once(value_column(spark.range(10).toDF("v"), "v")).rdd.getNumPartitions() == spark.range(10).rdd.getNumPartitions()


def test_the_repair_follows_candidates_times_partitions(spark, monkeypatch):
    df = column(spark, [float(i * 7919 % 5003) for i in range(5000)], "double", 8)
    for rows, how in ((10**6, "topk"), (10, "kernel")):
        monkeypatch.setattr(g, "TOPK_ROWS", rows)
        x = RunLedger()
        guided_quantile(df, "v", "0.5", eps=0.02, ledger=x)
        assert x.rank_err == 0 or (x.notes["extract"] == how and (x.buffer_peak > 0) == (how == "kernel"))


def test_plans(spark):
    df = load(spark, SF, "lineitem")
    near = value_column(df, "l_extendedprice").where(F.col("v") > 50000.0).orderBy("v").limit(10).agg(F.max("v"))
    text = near._jdf.queryExecution().toString()
    assert "TakeOrderedAndProject" in text and "GreaterThan(l_extendedprice" in text.replace("PushedFilters", "") and "l_orderkey" not in text.split("ReadSchema")[-1]


def test_groups(spark):
    rows = [(None if i % 5 == 0 else i % 3, float(i * 31 % 101) if i % 11 else None) for i in range(400)] + [(9, 1.0)]
    df = spark.createDataFrame(rows, "k int, v double")
    out = {r["k"]: (r["n"], r["value"]) for r in guided_quantile_by(df, ["k"], "v", 0.3, eps=0.1).collect()}
    for k in {k for k, _ in rows}:
        own = sorted(v for x, v in rows if x == k and v is not None)
        assert out[k] == (len(own), own[math.ceil(round(0.3 * len(own), 9)) - 1])


def test_ranks(spark):
    df = spark.createDataFrame([(i * 37 % 101, i) for i in range(101)], "a int, b int")
    assert [r["rk"] for r in rank_all(df, ["a"], partitions=5).orderBy("a").collect()] == list(range(101))
    assert tuple(rank_of_value(df, "a", 10).first())[:3] == (10, 1, 101)


def test_pruning_by_messages_on_the_distributions(spark):
    import duckdb

    from exactrank import catalog
    from exactrank.sources.distributions import DISTRIBUTIONS

    con = duckdb.connect()
    for t in ("lineitem", "orders", "events"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '/root/testdata/sf0.001/{t}.parquet'")
    names = [f"dist_{d}_{q}_{g}_prune" for d in DISTRIBUTIONS for q in ("p50", "p99") for g in ("tree", "collect")]
    assert {*names, "bench_size_x100"} <= set(catalog.queries())
    for name in ("dist_zipf_p50_tree_prune", "dist_uniform_p99_collect_prune"):
        got = catalog.queries()[name](spark, "/root/testdata/sf0.001").collect()
        cursor = con.execute(catalog.oracle_sql()[name])
        columns = [c[0] for c in cursor.description]
        assert [tuple(r[c] for c in columns) for r in got] == cursor.fetchall()
