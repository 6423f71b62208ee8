"""Tables written to the folder that driver and executors share, to cut lineage in loops."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

#: where a staged DataFrame keeps its folder
STAGED_AT = "_hopframe_staged_at"


def shared_path(spark: SparkSession) -> str:
    """A fresh path below ``spark.checkpoint.dir``, or below the warehouse where that is unset (tests, bench)."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_stage"
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


def staged(df: DataFrame) -> DataFrame:
    """``df`` written to the shared folder and read again."""
    spark = df.sparkSession
    path = shared_path(spark)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.__dict__[STAGED_AT] = path
    return out


def replaced(df: DataFrame, *old: DataFrame) -> DataFrame:
    """``df`` staged, after which the staged tables ``old``, which nothing else may read any more, are removed."""
    out = staged(df)
    dropped(*old)
    return out


def dropped(*old: DataFrame) -> None:
    """Removes staged tables. A remote session has no access to the file system and leaves them."""
    for df in old:
        path, jvm = df.__dict__.get(STAGED_AT), getattr(df.sparkSession, "_jvm", None)
        if path is None or jvm is None:
            continue
        place = jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(place, True)
