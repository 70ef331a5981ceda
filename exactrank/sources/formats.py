"""Reading and writing with fixed schemas: no inference, bad records kept apart."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

FORMATS = ("parquet", "orc", "csv", "json")
BAD = "_bad_record"


def read(spark: SparkSession, kind: str, path: str, schema: str) -> DataFrame:
    """Text formats parse permissively: a record that does not fit has its text in ``_bad_record``."""
    reader = spark.read
    if kind in ("csv", "json"):
        reader = reader.schema(f"{schema}, {BAD} string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", BAD)
        if kind == "csv":
            reader = reader.option("header", True).option("multiLine", True).option("escape", '"')
    else:
        reader = reader.schema(schema)
    return reader.format(kind).load(path)


def write(df: DataFrame, kind: str, path: str, partition_by: list[str] | None = None, sort_by: list[str] | None = None) -> None:
    """Partitioned and, within files, sorted output: later filters skip row groups."""
    if partition_by:
        df = df.repartition(*[F.col(c) for c in partition_by])
    if sort_by:
        df = df.sortWithinPartitions(*(partition_by or []), *sort_by)
    writer = df.write.format(kind).mode("errorifexists")
    if kind == "csv":
        writer = writer.option("header", True).option("escape", '"')
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
