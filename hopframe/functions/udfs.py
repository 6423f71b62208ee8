"""One query for each kind of user-defined function."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "user_id", "event_type", "value")


def udf_scalar(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A Python function of one row, sent in Arrow batches."""
    initials = F.udf(lambda s: "".join(w[0] for w in s.split("#")), "string", useArrow=True)
    return spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", initials("c_name").alias("i"))


def udf_pandas(spark: SparkSession, sf_dir: str) -> DataFrame:
    @F.pandas_udf("double")
    def bucket(x: pd.Series) -> pd.Series:
        return (x // 10) * 10.0

    return _events(spark, sf_dir).groupBy(bucket("value").alias("b")).agg(F.count("*").alias("n"))


def udaf_pandas(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A grouped aggregate over whole groups; groups must fit a worker, so it is for bounded ones."""

    @F.pandas_udf("double")
    def spread(x: pd.Series) -> float:
        return float(x.max() - x.min())

    return _events(spark, sf_dir).groupBy("event_type").agg(F.round(spread("value"), 6).alias("spread"))


def udtf_expand(spark: SparkSession, sf_dir: str) -> DataFrame:
    @F.udtf(returnType="step int, node bigint")
    class Upward:
        """The chain of parents of a part, by its number."""

        def eval(self, start: int):
            step = 0
            while start > 0:
                start, step = start // 10, step + 1
                yield step, start

    spark.udtf.register("upward", Upward)
    spark.read.parquet(f"{sf_dir}/part.parquet").select("p_partkey").createOrReplaceTempView("part_keys")
    return spark.sql("SELECT p_partkey, step, node FROM part_keys, LATERAL upward(p_partkey)")


def map_in_pandas(spark: SparkSession, sf_dir: str) -> DataFrame:
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            yield f.assign(high=f["value"] > 100)[["event_id", "high"]]

    return _events(spark, sf_dir).mapInPandas(run, "event_id long, high boolean").groupBy("high").agg(F.count("*").alias("n"))


def apply_in_pandas(spark: SparkSession, sf_dir: str) -> DataFrame:
    def run(f: pd.DataFrame) -> pd.DataFrame:
        f = f.sort_values("event_id")
        return f.assign(place=range(len(f)))[["event_id", "place"]]

    return _events(spark, sf_dir).groupBy("user_id").applyInPandas(run, "event_id long, place int")


QUERIES = {f.__name__: f for f in (udf_scalar, udf_pandas, udaf_pandas, udtf_expand, map_in_pandas, apply_in_pandas)}
ORACLES = {
    "udf_scalar": "SELECT c_custkey, list_aggregate(list_transform(string_split(c_name, '#'), lambda w: w[1]), 'string_agg', '') AS i FROM customer",
    "udf_pandas": "SELECT floor(value / 10) * 10.0::DOUBLE AS b, count(*) AS n FROM events GROUP BY 1",
    "udaf_pandas": "SELECT event_type, round(max(value) - min(value), 6) AS spread FROM events GROUP BY 1",
    "udtf_expand": "WITH RECURSIVE w AS (SELECT p_partkey, 1 AS step, p_partkey // 10 AS node FROM part WHERE p_partkey > 0 UNION ALL SELECT p_partkey, step + 1, node // 10 FROM w WHERE node > 0) SELECT p_partkey, step, node FROM w",
    "map_in_pandas": "SELECT value > 100 AS high, count(*) AS n FROM events GROUP BY 1",
    "apply_in_pandas": "SELECT event_id, row_number() OVER (PARTITION BY user_id ORDER BY event_id) - 1 AS place FROM events",
}
