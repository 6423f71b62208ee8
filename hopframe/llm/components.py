"""Connected components by least label with shortcuts, in DataFrame joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopframe.llm.common import staged


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component) for every node of an undirected link table; component is the least node reached.

    Each round takes the least label around every node, then follows that label's own label. Hot nodes cost a
    partial aggregate only. Each round's labels are written to the shared folder; rounds grow with the logarithm
    of a component's width in practice and end when no label moves.
    """
    ends = links.select(F.col(a).alias("u"), F.col(b).alias("v"))
    both = staged(ends.unionByName(ends.select(F.col("v").alias("u"), F.col("u").alias("v"))).where("u <> v").distinct())
    labels = staged(both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("node"), F.least("u", "m").alias("component")))
    while True:
        around = both.join(labels.select(F.col("node").alias("v"), "component"), "v").groupBy("u").agg(F.min("component").alias("m"))
        near = labels.join(around.withColumnRenamed("u", "node"), "node").select("node", F.col("component").alias("was"), F.least("component", "m").alias("c"))
        step = staged(near)
        jump = step.select(F.col("node").alias("c"), F.col("c").alias("further"))
        moved = staged(step.join(jump, "c", "left").select("node", "was", F.least("c", F.coalesce("further", "c")).alias("component")))
        labels = moved.select("node", "component")
        if moved.where("was <> component").isEmpty():
            return labels
