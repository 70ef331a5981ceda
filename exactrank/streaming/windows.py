"""Quantiles over event-time windows, and the stream operations around them."""

from __future__ import annotations

from datetime import timedelta

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from exactrank.plans.grouped import guided_quantile_by
from exactrank.sources.shared import scratch
from exactrank.sources.tables import SCHEMAS


def instant(ts: Column) -> Column:
    """A wall-clock time as the instant it names in UTC, whatever the session's zone: watermarks
    need instants."""
    return F.timestamp_micros(F.timestamp_diff("MICROSECOND", F.expr("TIMESTAMP_NTZ'1970-01-01 00:00:00'"), ts))


def wall_clock(t: Column) -> Column:
    """The inverse of ``instant``."""
    seconds = (F.unix_micros(t).cast("decimal(20,0)") / 1000000).cast("decimal(18,6)")
    return F.expr("TIMESTAMP_NTZ'1970-01-01 00:00:00'") + F.make_dt_interval(secs=seconds)


def event_stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """A file source with the fixed schema, ``ts`` as an instant; ``path`` holds Parquet files, oldest first."""
    rows = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return rows.withColumn("ts", instant(F.col("ts")))


def event_window(time: str, width: str, slide: str | None = None, gap: str | None = None):
    return F.session_window(time, gap) if gap else F.window(time, width, slide) if slide else F.window(time, width)


def windowed_quantile(stream: DataFrame, time: str, col: str, q: float, width: str, slide: str | None = None, gap: str | None = None, delay: str = "1 day", accuracy: int = 1000, keys: tuple[str, ...] = ()) -> DataFrame:
    """(start, end, keys, n, low, value, high): a sketch for each open window as state; low and high
    bound the exact quantile within 1 / accuracy of the ranks on either side."""
    eps = 1 / accuracy
    probs = [max(q - 2 * eps, 0.0), q, min(q + 2 * eps, 1.0)]
    grouped = stream.withWatermark(time, delay).groupBy(event_window(time, width, slide, gap).alias("w"), *keys)
    out = grouped.agg(F.count(col).alias("n"), F.percentile_approx(col, probs, accuracy).alias("p"))
    return out.select(wall_clock(F.col("w.start")).alias("start"), wall_clock(F.col("w.end")).alias("end"), *keys, "n", F.col("p")[0].alias("low"), F.col("p")[1].alias("value"), F.col("p")[2].alias("high"))


def run_to_table(stream: DataFrame, mode: str = "append", label: str = "stream") -> DataFrame:
    """Process all there is now, into a table in the shared folder (append), or the last state of
    an updating result (complete), and return it as a batch."""
    spark = stream.sparkSession
    where, marks = scratch(spark, label), scratch(spark, f"{label}-marks")
    schema = stream.schema
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", where).option("checkpointLocation", marks).outputMode("append").trigger(availableNow=True).start()
    else:

        def keep(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(where)

        query = stream.writeStream.foreachBatch(keep).option("checkpointLocation", marks).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    if query.exception():
        raise query.exception()
    return spark.read.schema(schema).parquet(where)


def exact_on_closed_windows(stream: DataFrame, time: str, col: str, q: float, width: str, delay: timedelta, keys: tuple[str, ...] = ()) -> DataFrame:
    """Exact quantiles of windows that can no longer change. Rows wait in a table; a batch that
    closes windows (those ending by the latest time less the delay) runs guided selection on their
    rows alone. Late rows of closed windows are left out, as a watermark does."""
    spark = stream.sparkSession
    held, results, marks = scratch(spark, "held"), scratch(spark, "closed"), scratch(spark, "closed-marks")
    state = {"latest": None, "closed": None, "batches": 0}
    columns = [time, col, *keys]

    def step(batch: DataFrame, number: int) -> None:
        rows = batch.select(*columns).withColumn("w", F.window(time, width)).select("*", F.col("w.start").alias("start"), F.col("w.end").alias("end")).drop("w")
        if state["closed"] is not None:
            rows = rows.where(F.col("end") > F.lit(state["closed"]))
        rows.write.mode("overwrite").parquet(f"{held}/batch={number}")
        latest = batch.agg(F.max(time)).first()[0]
        if latest is not None and (state["latest"] is None or latest > state["latest"]):
            state["latest"] = latest
        edge = state["latest"] - delay if state["latest"] is not None else None
        if edge is None:
            return
        waiting = spark.read.schema(rows.schema).parquet(held)
        due = waiting.where(F.col("end") <= F.lit(edge))
        if state["closed"] is not None:
            due = due.where(F.col("end") > F.lit(state["closed"]))
        guided_quantile_by(due, ["start", "end", *keys], col, q).write.mode("overwrite").parquet(f"{results}/batch={number}")
        state["closed"] = edge

    query = stream.writeStream.foreachBatch(step).option("checkpointLocation", marks).trigger(availableNow=True).start()
    query.awaitTermination()
    kind = stream.schema
    schema = f"start timestamp, end timestamp, {''.join(f'{k} {kind[k].dataType.simpleString()}, ' for k in keys)}n long, value {kind[col].dataType.simpleString()}"
    out = spark.read.schema(schema).parquet(results)
    return out.select(wall_clock(F.col("start")).alias("start"), wall_clock(F.col("end")).alias("end"), *keys, "n", "value")
