"""Streams over events, run to the end of the input: windows, sessions, distinct rows, joins with labels."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semjoin.models import UNKNOWN
from semjoin.sources.tables import load, work_folder

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
DELAY = "2 days"


def query(sql: str):
    def add(f):
        QUERIES[f.__name__], ORACLES[f.__name__] = f, sql
        return f

    return add


def events_stream(spark: SparkSession, sf_dir: str, delay: str = DELAY) -> DataFrame:
    """events as a stream with a watermark; the stored time has no zone, which watermarks need."""
    schema = load(spark, sf_dir, "events").schema
    rows = spark.readStream.schema(schema).parquet(f"{sf_dir}/event[s].parquet")
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def drain(df: DataFrame, mode: str = "append", base: str | None = None) -> DataFrame:
    """Run a stream over all input there is and return what it wrote. Complete results, which have a row for each
    open window, go through foreachBatch so that the last batch stands. With the base of an earlier run the stream
    goes on where that one ended."""
    spark = df.sparkSession
    base = base or f"{work_folder(spark)}/stream-{uuid.uuid4().hex}"
    writer = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{base}/checkpoint")
    if mode == "append":
        writer.format("parquet").start(f"{base}/out").awaitTermination()
    else:
        writer.foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(f"{base}/out")).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{base}/out")


@query("SELECT event_type, strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    e = events_stream(spark, sf_dir).groupBy("event_type", F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    return drain(e, "complete").select("event_type", F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 12 HOUR]) AS s FROM events) x GROUP BY 1")
def stream_sliding(spark, sf_dir):
    e = events_stream(spark, sf_dir).groupBy(F.window("ts", "24 hours", "12 hours")).agg(F.count(F.lit(1)).alias("n"))
    return drain(e, "complete").select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events) a) b GROUP BY user_id, s")
def stream_session(spark, sf_dir):
    e = events_stream(spark, sf_dir).groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count(F.lit(1)).alias("n"))
    return drain(e, "complete").select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


_ON_TIME = "SELECT event_type, ts, max(ts) OVER () - INTERVAL 2 DAY AS mark FROM events WHERE event_id % 10 <> 0"


@query(f"SELECT event_type, strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM ({_ON_TIME}) e WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= mark GROUP BY 1, 2")
def stream_late_rows(spark, sf_dir):
    """A tenth of the events comes in a second run, behind the watermark of the first: windows that have been
    closed stand as they are, and those still open are not written."""
    rows, base = load(spark, sf_dir, "events"), f"{work_folder(spark)}/stream-{uuid.uuid4().hex}"
    late = F.coalesce(F.col("event_id") % 10 == 0, F.lit(False))
    for part in (rows.where(~late), rows.where(late)):
        part.write.mode("append").parquet(f"{base}/events.parquet")
        daily = events_stream(spark, base).groupBy("event_type", F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
        out = drain(daily, base=f"{base}/run")
    return out.select("event_type", F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, sf_dir):
    return drain(events_stream(spark, sf_dir, "60 days").select("user_id", "event_type", "ts").dropDuplicates(["user_id", "event_type"])).select("user_id", "event_type")


def label_join_stream(left: DataFrame, right: DataFrame, hours: int = 2) -> DataFrame:
    """Rows (id, label, ts) of two streams with the same known label, at most `hours` apart; state older
    than the watermark and the bound goes. Labels are a fixed function of the row, so replays agree.

    Time is cut into slots of `hours`. A row of the left is in its slot, one of the right in its own and both beside it, so
    each pair meets in one slot, and a row is compared with what is near it in time, not with all of its label."""
    width = max(1, hours) * 3_600_000_000
    slot = lambda t: F.expr(f"(unix_micros({t}) - pmod(unix_micros({t}), {width}L)) div {width}L")
    a = left.where(F.col("label") != UNKNOWN).select(F.col("id").alias("a_id"), F.col("label").alias("la"), F.col("ts").alias("ta"), slot("ts").alias("sa"))
    b = right.where(F.col("label") != UNKNOWN).select(F.col("id").alias("b_id"), F.col("label").alias("lb"), F.col("ts").alias("tb"), F.explode(F.sequence(slot("ts") - 1, slot("ts") + 1)).alias("sb"))
    near = F.expr(f"la = lb and sa = sb and tb >= ta - interval {hours} hours and tb <= ta + interval {hours} hours")
    return a.join(b, near).select("a_id", "b_id")


_SIDE = "(SELECT event_id AS id, concat('person ', CAST(user_id % 9 AS VARCHAR)) AS label, ts FROM events WHERE event_type = '{}' AND user_id % 9 < 8)"


@query(f"SELECT a.id AS a_id, b.id AS b_id FROM {_SIDE.format('error')} a JOIN {_SIDE.format('signup')} b ON a.label = b.label AND b.ts BETWEEN a.ts - INTERVAL 2 HOUR AND a.ts + INTERVAL 2 HOUR")
def stream_label_join(spark, sf_dir):
    label = F.when(F.col("user_id") % 9 < 8, F.concat(F.lit("person "), (F.col("user_id") % 9).cast("string"))).otherwise(F.lit(UNKNOWN))
    side = lambda kind: events_stream(spark, sf_dir).where(F.col("event_type") == kind).select(F.col("event_id").alias("id"), label.alias("label"), "ts")
    return drain(label_join_stream(side("error"), side("signup")))
