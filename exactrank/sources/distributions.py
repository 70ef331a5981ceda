"""Four value distributions in [-1e9, 1e9), made from table keys in integer arithmetic, so that
any SQL engine makes the same values: uniform, Zipf (s = 2.5), bimodal, sorted bands."""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from exactrank.operators.joins import range_join
from exactrank.sources.tables import load

MODULUS = 2147483647
MULTIPLIER = 48271
ZIPF_VALUES = 1000
ZIPF_S = 2.5
SEED = f"(l_orderkey * 48271 + l_partkey * 16807 + l_suppkey * 69621 + l_linenumber * 39373 + CAST(round(l_extendedprice * 100) AS BIGINT) * 7919) % {MODULUS}"


def zipf_thresholds() -> list[tuple[int, int, int]]:
    """(value, from, to): draws in [from, to) take the value."""
    weights = [j**-ZIPF_S for j in range(1, ZIPF_VALUES + 1)]
    total = sum(weights)
    ends = [int(MODULUS * h / total) for h in accumulate(weights)]
    ends[-1] = MODULUS
    return [((j + 1) * 387420489 % 2000000000 - 1000000000, ends[j - 1] if j else 0, ends[j]) for j in range(ZIPF_VALUES)]


def _draw(i: int) -> str:
    """The i-th number of a multiplicative generator, straight from its start."""
    return f"x0 * {pow(MULTIPLIER, i, MODULUS)} % {MODULUS}"


def draws(spark: SparkSession, sf_dir: str, n: int = 13) -> DataFrame:
    """x1..xn for each row of lineitem, started from its keys."""
    df = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice")
    return df.selectExpr(f"{SEED} AS x0").selectExpr(*[f"{_draw(i)} AS x{i}" for i in range(1, n + 1)])


def uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return draws(spark, sf_dir, 1).selectExpr(f"x1 * 2000000000 div {MODULUS} - 1000000000 AS v")


def bimodal(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two bells at +-3.33e8, each a sum of twelve uniforms, kept within the range."""
    total = " + ".join(f"x{i}" for i in range(1, 13))
    v = f"CASE WHEN x13 % 2 = 0 THEN -333000000 ELSE 333000000 END + ({total}) * 166000000 div {MODULUS} - 996000000"
    return draws(spark, sf_dir).selectExpr(f"CAST(least(greatest({v}, -1000000000), 999999999) AS BIGINT) AS v")


def zipf(spark: SparkSession, sf_dir: str) -> DataFrame:
    table = spark.createDataFrame(zipf_thresholds(), "v long, lo long, hi long")
    return range_join(draws(spark, sf_dir, 1).select("x1"), "x1", F.broadcast(table), "lo", "hi", 1 << 21).select("v")


def sorted_bands(spark: SparkSession, sf_dir: str, parts: int = 8) -> DataFrame:
    """Each partition is a disjoint sorted band of the uniform values."""
    return uniform(spark, sf_dir).repartitionByRange(parts, "v").sortWithinPartitions("v")


def enlarged(values: DataFrame, times: int) -> DataFrame:
    """``times`` as many values: copies shifted by an odd multiple of their number within the range."""
    copies = values.sparkSession.range(times).withColumnRenamed("id", "copy")
    return values.join(F.broadcast(copies)).selectExpr("pmod(v + 1000000000 + copy * 7368787, 2000000000) - 1000000000 AS v")


DISTRIBUTIONS = {"uniform": uniform, "zipf": zipf, "bimodal": bimodal, "sorted": sorted_bands}


def duckdb_sql(name: str) -> str:
    """The same values as a DuckDB query with one column v."""
    drawn = ", ".join(f"{_draw(i)} AS x{i}" for i in range(1, 14 if name == "bimodal" else 2))
    chain = f"SELECT {drawn} FROM (SELECT {SEED} AS x0 FROM lineitem)"
    if name == "bimodal":
        total = " + ".join(f"x{i}" for i in range(1, 13))
        return f"SELECT least(greatest(CASE WHEN x13 % 2 = 0 THEN -333000000 ELSE 333000000 END + ({total}) * 166000000 // {MODULUS} - 996000000, -1000000000), 999999999)::BIGINT AS v FROM ({chain})"
    if name == "zipf":
        rows = ", ".join(str(t) for t in zipf_thresholds())
        return f"SELECT t.v FROM ({chain}) JOIN (VALUES {rows}) t(v, lo, hi) ON x1 >= lo AND x1 < hi"
    return f"SELECT x1 * 2000000000 // {MODULUS} - 1000000000 AS v FROM ({chain})"
