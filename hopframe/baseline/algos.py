"""Vertex programs as joins: PageRank, shortest distances, weakly connected components."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopframe.exec.staging import replaced, staged
from hopframe.paths.forms import shortest


def pagerank(link: DataFrame, damping: float = 0.85, rounds: int = 10) -> DataFrame:
    """(node, rank) after ``rounds`` rounds from equal ranks; nodes without out-edges give their rank to nobody."""
    edges = staged(link.select("s0", "t0"))
    nodes = staged(edges.select(F.col("s0").alias("node")).unionAll(edges.select(F.col("t0").alias("node"))).distinct())
    count = nodes.count()
    degree = edges.groupBy("s0").agg(F.count("*").alias("degree"))
    flows = staged(edges.join(degree, "s0"))
    ranks = nodes.withColumn("rank", F.lit(1.0 / count if count else 0.0))
    for _ in range(rounds):
        sent = flows.join(ranks.select(F.col("node").alias("s0"), "rank"), "s0").groupBy(F.col("t0").alias("node")).agg(F.sum(F.col("rank") / F.col("degree")).alias("got"))
        ranks = replaced(nodes.join(sent, "node", "left").select("node", (F.lit((1 - damping) / max(count, 1)) + damping * F.coalesce("got", F.lit(0.0))).alias("rank")), ranks)
    return ranks


def sssp(link: DataFrame, source: DataFrame, weight: str | None = None) -> DataFrame:
    """(s0, t0, cost) from the sources to all they reach."""
    everyone = link.select("t0").unionAll(link.select(F.col("s0").alias("t0")))
    return shortest(link, source, everyone, weight).select("s0", "t0", "cost")


def wcc(link: DataFrame) -> DataFrame:
    """(node, component): least node reachable when directions are ignored; labels jump along themselves each round."""
    both = staged(link.select(F.col("s0").alias("u"), F.col("t0").alias("v")).unionAll(link.select(F.col("t0").alias("u"), F.col("s0").alias("v"))).distinct())
    labels = staged(both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("node"), F.least("u", "m").alias("component")))
    before = labels
    while True:
        around = both.join(labels.select(F.col("node").alias("v"), "component"), "v").groupBy(F.col("u").alias("node")).agg(F.min("component").alias("m"))
        near = staged(labels.join(around, "node").select("node", F.col("component").alias("was"), F.least("component", "m").alias("c")))
        jump = near.select(F.col("node").alias("c"), F.col("c").alias("further"))
        moved = replaced(near.join(jump, "c", "left").select("node", "was", F.least("c", F.coalesce("further", "c")).alias("component")), near, before)
        labels, before = moved.select("node", "component"), moved
        if moved.where("was <> component").isEmpty():
            return labels
