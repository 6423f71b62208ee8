"""Round trips through the other file formats, and partitioned and bucketed sinks."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from hopframe.exec.staging import shared_path


def round_trip(df: DataFrame, kind: str, schema: StructType | None = None, **options: str) -> DataFrame:
    """``df`` written in a format and read again with an explicit schema."""
    spark, path = df.sparkSession, shared_path(df.sparkSession)
    df.write.format(kind).options(**options).save(path)
    return spark.read.format(kind).options(**options).schema(schema or df.schema).load(path)


def partitioned(df: DataFrame, *columns: str) -> DataFrame:
    """Written as Parquet with a folder for each value, then read back; filters on the columns prune folders."""
    path = shared_path(df.sparkSession)
    df.repartition(*columns).write.partitionBy(*columns).parquet(path)
    return df.sparkSession.read.parquet(path)


def bucketed(df: DataFrame, buckets: int, *columns: str) -> DataFrame:
    """A warehouse table bucketed and sorted by ``columns``; joins of two such tables on them need no exchange."""
    name = f"bucketed_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, *columns).sortBy(*columns).option("path", shared_path(df.sparkSession)).saveAsTable(name)
    return df.sparkSession.table(name)


def _nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/nation.parquet")


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "user_id", "event_type", "props")


def src_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = _nation(spark, sf_dir).select(F.concat_ws("|", F.col("n_nationkey").cast("string"), "n_name").alias("value"))
    back = round_trip(lines, "text")
    return back.select(F.split("value", "\\|")[0].cast("int").alias("n_nationkey"), F.split("value", "\\|")[1].alias("n_name"))


def sink_bucketed(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = bucketed(spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_custkey", "o_orderkey"), 8, "o_custkey")
    customers = bucketed(spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment"), 8, "o_custkey")
    return orders.join(customers.hint("merge"), "o_custkey").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


_NATIONS = "SELECT n_nationkey, n_name, n_regionkey FROM nation"
_EVENTS = "SELECT event_id, user_id, event_type, props FROM events"
QUERIES = {
    "src_csv": lambda spark, d: round_trip(_nation(spark, d), "csv", header="true"),
    "src_json": lambda spark, d: round_trip(_events(spark, d), "json"),
    "src_orc": lambda spark, d: round_trip(_events(spark, d), "orc"),
    "src_text": src_text,
    "sink_parquet_partitioned": lambda spark, d: partitioned(_events(spark, d), "event_type").where("event_type = 'click'").groupBy("user_id").agg(F.count("*").alias("n")),
    "sink_bucketed": sink_bucketed,
}
ORACLES = {
    "src_csv": _NATIONS,
    "src_json": _EVENTS,
    "src_orc": _EVENTS,
    "src_text": "SELECT n_nationkey, n_name FROM nation",
    "sink_parquet_partitioned": "SELECT user_id, count(*) AS n FROM events WHERE event_type = 'click' GROUP BY 1",
    "sink_bucketed": "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1",
}
