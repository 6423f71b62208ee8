"""Joins that Spark has no operator for, composed of ones that it has."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def range_join(points: DataFrame, ranges: DataFrame, at: str, low: str, high: str, width: float) -> DataFrame:
    """Rows of ``points`` with ``low <= at < high`` of ``ranges``: an equi-join on bins of ``width`` and a residual.

    Each range is repeated for the bins it touches, so ``width`` should be near the usual length of a range.
    """
    binned = points.withColumn("_bin", F.floor(F.col(at).cast("double") / width))
    first, last = F.floor(F.col(low).cast("double") / width), F.floor(F.col(high).cast("double") / width)
    spread = ranges.withColumn("_bin", F.explode(F.sequence(first, last)))
    return binned.join(spread, "_bin").where((F.col(at) >= F.col(low)) & (F.col(at) < F.col(high))).drop("_bin")


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str, tie: str) -> DataFrame:
    """Each row of ``left`` with the newest ``value`` of ``right`` at or before ``at`` under the same key.

    Both sides are laid over each other once and swept by a window; no row is compared with another. Rights that
    stand at the same time are ordered by ``tie``.
    """
    a = left.select("*", F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side"), F.lit(None).cast(right.schema[tie].dataType).alias("_tie"))
    b = right.select(key, at, F.col(value).alias("_v"), F.lit(0).alias("_side"), F.col(tie).alias("_tie"))
    order = W.partitionBy(key).orderBy(at, "_side", "_tie").rowsBetween(W.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True).withColumn(value, F.last("_v", ignorenulls=True).over(order))
    return both.where("_side = 1").drop("_v", "_side", "_tie")


def salted_join(big: DataFrame, small: DataFrame, key: str, salts: int, spread: Column) -> DataFrame:
    """An equi-join in which every key of ``big`` is dealt over ``salts`` partitions and ``small`` is repeated."""
    a = big.withColumn("_salt", F.pmod(F.xxhash64(spread), F.lit(salts)).cast("int"))
    b = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [key, "_salt"]).drop("_salt")
