"""Cyclic patterns with bounded intermediate results."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def undirected_triangles(link: DataFrame) -> DataFrame:
    """(a, b, c) of every triangle once. Edges run from the lower degree to the higher, which bounds every fan-out by
    the square root of the number of edges; hubs hold no long lists."""
    pairs = link.where("s0 <> t0").select(F.least("s0", "t0").alias("x"), F.greatest("s0", "t0").alias("y")).distinct()
    ends = pairs.select(F.col("x").alias("v")).unionAll(pairs.select(F.col("y").alias("v")))
    degree = ends.groupBy("v").agg(F.count("*").alias("d"))
    ranked = pairs.join(degree.select(F.col("v").alias("x"), F.col("d").alias("dx")), "x").join(degree.select(F.col("v").alias("y"), F.col("d").alias("dy")), "y")
    forward = (F.col("dx") < F.col("dy")) | ((F.col("dx") == F.col("dy")) & (F.col("x") < F.col("y")))
    up = ranked.select(F.when(forward, F.col("x")).otherwise(F.col("y")).alias("u"), F.when(forward, F.col("y")).otherwise(F.col("x")).alias("v"))
    wedge = up.select("u", F.col("v").alias("p")).join(up.select("u", F.col("v").alias("q")), "u").where("p < q")
    closed = wedge.join(pairs.select(F.col("x").alias("p"), F.col("y").alias("q")), ["p", "q"])
    return closed.select(F.sort_array(F.array("u", "p", "q")).alias("t")).select(*(F.col("t")[i].alias(n) for i, n in enumerate("abc")))


def directed_triangles(link: DataFrame) -> DataFrame:
    """(a, b, c) of every directed cycle of three distinct nodes, once, from its least node.

    Undirected triangles bound the candidates; the two ways round each are held against the arcs.
    """
    arcs = link.where("s0 <> t0").select("s0", "t0").distinct()
    found = undirected_triangles(link)
    ways = found.unionAll(found.select("a", F.col("c").alias("b"), F.col("b").alias("c")))
    for x, y in ("ab", "bc", "ca"):
        ways = ways.join(arcs.select(F.col("s0").alias(x), F.col("t0").alias(y)), [x, y], "left_semi")
    return ways.select("a", "b", "c")
