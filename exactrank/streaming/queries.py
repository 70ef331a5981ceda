"""Registered stream queries: run over all files there are, returned as batch tables."""

from __future__ import annotations

from datetime import timedelta

from pyspark.sql import functions as F

from exactrank.plans.guided import count_around
from exactrank.plans.values import value_column
from exactrank.sources.shared import scratch
from exactrank.sources.tables import load
from exactrank.streaming.state import summary_state
from exactrank.streaming.windows import event_stream, exact_on_closed_windows, run_to_table, wall_clock, windowed_quantile

QUERIES: dict = {}
SQL: dict[str, str] = {}
FILES = 4


def query(sql: str | None = None):
    def keep(fn):
        QUERIES[fn.__name__] = fn
        if sql:
            SQL[fn.__name__] = sql
        return fn

    return keep


def replay(s, d, late: bool = False):
    """The events as a stream of files in time order; ``late``: every 50th row comes with the last."""
    e = load(s, d, "events")
    low, high = e.agg(F.unix_micros(F.min("ts").cast("timestamp")), F.unix_micros(F.max("ts").cast("timestamp"))).first()
    part = F.least(F.floor((F.unix_micros(F.col("ts").cast("timestamp")) - low) * FILES / (high - low + 1)), F.lit(FILES - 1)).cast("int")
    if late:
        part = F.when(F.col("event_id") % 50 == 0, FILES - 1).otherwise(part)
    path = scratch(s, "replay")
    staged = e.withColumn("part", part)
    for i in range(FILES):  # one file after another, so that the source sees them in order
        staged.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(path)
    return event_stream(s, path)


_CLOSED = "(SELECT max(ts) FROM events) - INTERVAL 1 DAY"


@query(f"SELECT * FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, sum(value::DECIMAL(18,6))::DOUBLE AS total FROM events GROUP BY 1, 2) WHERE start + INTERVAL 1 HOUR <= {_CLOSED}")
def stream_tumble_totals(s, d):
    rows = replay(s, d).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum(F.col("value").cast("decimal(18,6)")).alias("total"))
    return run_to_table(rows.select(wall_clock(F.col("w.start")).alias("start"), "event_type", "n", F.col("total").cast("double").alias("total")))


@query(f"SELECT * FROM (SELECT time_bucket(INTERVAL 1 HOUR, t) AS start, count(*) AS n FROM (SELECT ts AS t FROM events UNION ALL SELECT ts - INTERVAL 1 HOUR FROM events) GROUP BY 1) WHERE start + INTERVAL 2 HOUR <= {_CLOSED}")
def stream_slide_counts(s, d):
    rows = replay(s, d).withWatermark("ts", "1 day").groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return run_to_table(rows.select(wall_clock(F.col("w.start")).alias("start"), "n"))


@query(f"""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
r AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS run FROM g)
SELECT user_id, min(ts) AS start, count(*) AS n FROM r GROUP BY user_id, run HAVING max(ts) + INTERVAL 12 HOUR <= {_CLOSED}""")
def stream_session_counts(s, d):
    rows = replay(s, d).withWatermark("ts", "1 day").groupBy(F.session_window("ts", "12 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return run_to_table(rows.select("user_id", wall_clock(F.col("w.start")).alias("start"), "n"))


@query(f"SELECT count(*) AS windows, true AS within_bound FROM (SELECT DISTINCT time_bucket(INTERVAL 1 DAY, ts) AS start FROM events) WHERE start + INTERVAL 1 DAY <= {_CLOSED}")
def stream_tumble_p50_bound(s, d):
    """Each closed day's exact median lies between the sketch's bounds."""
    got = run_to_table(windowed_quantile(replay(s, d), "ts", "value", 0.5, "1 day", accuracy=100))
    exact = load(s, d, "events").groupBy(F.date_trunc("day", "ts").cast("timestamp_ntz").alias("start")).agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY value)").alias("mid"))
    both = got.join(exact, "start")
    return both.agg(F.count("*").alias("windows"), F.bool_and((F.col("mid") >= F.col("low")) & (F.col("mid") <= F.col("high"))).alias("within_bound"))


@query("SELECT event_type, count(*) AS n, true AS within_bound FROM events GROUP BY 1")
def stream_state_summary(s, d):
    """The last answer of each type's summary is within the bound of its exact rank."""
    path, marks = scratch(s, "state"), scratch(s, "state-marks")

    def keep(batch, number):
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/number={number}")

    stream = summary_state(replay(s, d), "event_type", "value", 0.02)
    stream.writeStream.foreachBatch(keep).option("checkpointLocation", marks).outputMode("update").trigger(availableNow=True).start().awaitTermination()
    last = s.read.schema("event_type string, n long, value double, batch int").parquet(path).groupBy("event_type").agg(F.max_by("n", "batch").alias("n"), F.max_by("value", "batch").alias("value"))
    rows, e = [], load(s, d, "events")
    for r in last.collect():  # one row for each event type
        n, ((below, equal),) = count_around(value_column(e.where(F.col("event_type") == r["event_type"]), "value"), [r["value"]])
        rows.append((r["event_type"], r["n"], max(0, below - n // 2, n // 2 - below - equal) <= 0.02 * n + 1))
    return s.createDataFrame(rows, "event_type string, n long, within_bound boolean")


@query("SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def stream_dedup(s, d):
    """Each event arrives twice; the second copy goes."""
    twice = replay(s, d).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    once = twice.withWatermark("ts", "2 days").dropDuplicatesWithinWatermark(["event_id"])
    return run_to_table(once.select("event_type")).groupBy("event_type").agg(F.count("*").alias("n"))


@query("SELECT r_name, count(*) AS n FROM events JOIN nation ON user_id % 25 = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def stream_static_join(s, d):
    places = load(s, d, "nation").join(load(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    joined = replay(s, d).join(F.broadcast(places), (F.col("user_id") % 25).cast("int") == F.col("n_nationkey"))
    return run_to_table(joined.select("r_name")).groupBy("r_name").agg(F.count("*").alias("n"))


@query("SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def stream_stream_join(s, d):
    a = replay(s, d).where("event_type = 'click'").select(F.col("event_id").alias("first_id"), F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", "1 day")
    b = replay(s, d).where("event_type = 'purchase'").select(F.col("event_id").alias("second_id"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", "1 day")
    return run_to_table(a.join(b, F.expr("u1 = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL 1 HOUR")).select("first_id", "second_id"))


@query("SELECT true AS dropped_late, true AS kept_rest")
def stream_late_drop(s, d):
    """With every 50th event arriving last, windows that were closed by then lack just those."""
    rows = replay(s, d, late=True).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
    got = run_to_table(rows.select(wall_clock(F.col("w.start")).alias("start"), "n"))
    day = F.date_trunc("day", "ts").cast("timestamp_ntz").alias("start")
    full = load(s, d, "events").groupBy(day).agg(F.count("*").alias("all"), F.count_if(F.col("event_id") % 50 != 0).alias("timely"))
    both = got.join(full, "start")
    return both.agg((F.sum("n") < F.sum("all")).alias("dropped_late"), F.bool_and(F.col("n").isin(F.col("all"), F.col("timely")) | (F.col("n") >= F.col("timely"))).alias("kept_rest"))


@query(f"""SELECT start, start + INTERVAL 1 DAY AS "end", event_type, n, value FROM (SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, event_type, count(*) AS n, quantile_disc(value, 0.5) AS value FROM events GROUP BY 1, 2)
WHERE start + INTERVAL 1 DAY <= {_CLOSED}""")
def stream_exact_closed_window(s, d):
    return exact_on_closed_windows(replay(s, d), "ts", "value", 0.5, "1 day", timedelta(days=1), ("event_type",))
