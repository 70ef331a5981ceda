"""Reading, materialising and naming helpers that all the document operators share."""

from __future__ import annotations

import gc
import time
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from exactrank.sources.shared import shared_dir

def documents(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet").select(*columns)


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back.

    Lineage ends at replicated files, so a lost executor costs no recomputation of what
    stands before. The files go when the JVM ends, or earlier through ``discard``.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(target)
    back = spark.read.schema(df.schema).parquet(path)
    back._written_at = path
    return back


def discard(df: DataFrame) -> None:
    """Delete the files behind a table made by ``materialise``; nothing may read it later."""
    spark = df.sparkSession
    path = getattr(df, "_written_at", None)
    if path:
        target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def release_shuffles(spark: SparkSession) -> None:
    """Have Spark's cleaner drop the shuffle files of plans that nothing refers to any more, such
    as those behind a table that ``materialise`` has written. Otherwise they stay until the
    driver's heap fills. The Python side lets go of its objects in the JVM once a second, so the
    JVM is asked after that, and again for what the first pass leaves unreachable."""
    gc.collect()
    for wait in (1.5, 0.5):
        time.sleep(wait)
        spark.sparkContext._jvm.System.gc()


def own_name(df: DataFrame, base: str) -> str:
    """A column name that ``df`` does not have."""
    taken = {c.lower() for c in df.columns}
    while base.lower() in taken:
        base = "_" + base
    return base


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def text_or_empty(column: str = "text"):
    return F.coalesce(F.col(column), F.lit(""))
