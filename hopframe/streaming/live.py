"""Streaming operators on the events, run to the end of what is there (``availableNow``)."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hopframe.sources.files import shared_path


def stream(spark: SparkSession, sf_dir: str, watermark: str | None = None) -> DataFrame:
    """Events with an instant ``at`` beside the zone-free ``ts``."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir).withColumn("at", F.col("ts").cast("timestamp"))
    return rows.withWatermark("at", watermark) if watermark else rows


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """The stream's result as a table, after all input there is. Files and state are in the shared folder."""
    spark, path = df.sparkSession, shared_path(df.sparkSession)
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", path + "_state").trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").option("path", path).start()
    else:
        query = writer.foreachBatch(lambda rows, _: rows.write.mode("overwrite" if mode == "complete" else "append").parquet(path)).start()
    query.awaitTermination()
    return spark.read.schema(df.schema).parquet(path)


def _plain(column: str):
    return F.col(column).cast("timestamp_ntz")


def st_passthrough(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drained(stream(spark, sf_dir).where("value > 100").select("event_id", "user_id"))


def st_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return drained(stream(spark, sf_dir).join(customers, "user_id").select("event_id", "c_mktsegment"))


def st_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = stream(spark, sf_dir).groupBy(F.window("at", "6 hours").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return drained(out, "complete").select(_plain("w.start").alias("start"), "event_type", "n")


def st_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = stream(spark, sf_dir).groupBy(F.window("at", "6 hours", "3 hours").alias("w")).agg(F.count("*").alias("n"))
    return drained(out, "complete").select(_plain("w.start").alias("start"), "n")


def st_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = stream(spark, sf_dir).groupBy(F.session_window("at", "2 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drained(out, "complete").groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"))


def st_dedup_watermark(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = stream(spark, sf_dir, "60 days").select("user_id", "event_type", "at")
    return drained(rows.dropDuplicatesWithinWatermark(["user_id", "event_type"])).select("user_id", "event_type")


def st_last_touch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Newest event of each user, kept in state by user."""

    def run(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        best = state.get if state.exists else (-1, -1)
        for f in frames:
            best = max([best, *zip(f["micros"].tolist(), f["event_id"].tolist())])
        state.update(best)
        yield pd.DataFrame({"user_id": [key[0]], "micros": [best[0]], "event_id": [best[1]]})

    rows = stream(spark, sf_dir).select("user_id", "event_id", F.unix_micros("at").alias("micros"))
    out = rows.groupBy("user_id").applyInPandasWithState(run, "user_id long, micros long, event_id long", "micros long, event_id long", "update", "NoTimeout")
    return drained(out, "update").groupBy("user_id").agg(F.max(F.struct("micros", "event_id")).alias("x")).select("user_id", "x.event_id")


def st_late_drop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Only windows that the watermark has closed are given out."""
    out = stream(spark, sf_dir, "1 day").groupBy(F.window("at", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return drained(out).select(_plain("w.start").alias("start"), "n")


def st_two_hop_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases within three hours of the same user's click: a join of two streams on an interval."""
    rows = stream(spark, sf_dir, "60 days")
    clicks = rows.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("at").alias("click_at"))
    buys = rows.where("event_type = 'purchase'").select(F.col("event_id").alias("buy"), "user_id", F.col("at").alias("buy_at"))
    near = (F.col("u") == F.col("user_id")) & (F.col("buy_at") >= F.col("click_at")) & (F.col("buy_at") < F.col("click_at") + F.expr("interval 3 hours"))
    return drained(clicks.join(buys, near).select("click", "buy"))


QUERIES = {f.__name__: f for f in (st_passthrough, st_static_join, st_tumbling, st_sliding, st_session, st_dedup_watermark, st_last_touch, st_late_drop, st_two_hop_interval)}
ORACLES = {
    "st_passthrough": "SELECT event_id, user_id FROM events WHERE value > 100",
    "st_static_join": "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey",
    "st_tumbling": "SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2000-01-01') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "st_sliding": "SELECT time_bucket(INTERVAL 3 HOUR, ts, TIMESTAMP '2000-01-01') - INTERVAL 3 HOUR * back AS start, count(*) AS n FROM events, (VALUES (0), (1)) b(back) GROUP BY 1",
    "st_session": "WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM g), c AS (SELECT user_id, k, count(*) AS n FROM s GROUP BY 1, 2) SELECT user_id, count(*) AS sessions, max(n) AS longest FROM c GROUP BY 1",
    "st_dedup_watermark": "SELECT DISTINCT user_id, event_type FROM events",
    "st_last_touch": "SELECT user_id, arg_max(event_id, (ts, event_id)) AS event_id FROM events GROUP BY 1",
    "st_late_drop": "SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2000-01-01') AS start, count(*) AS n FROM events GROUP BY 1 HAVING start + INTERVAL 6 HOUR <= (SELECT max(ts) - INTERVAL 1 DAY FROM events)",
    "st_two_hop_interval": "SELECT a.event_id AS click, b.event_id AS buy FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 3 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'",
}
