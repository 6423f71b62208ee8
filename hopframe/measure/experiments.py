"""The experiments as measurements: growth, cold and cached runs, storage forms, memory boundary, path forms, tax.

``python -m hopframe.measure.experiments SMALL_DIR LARGE_DIR [RUNS]`` prints one JSON line for each of them.
"""

from __future__ import annotations

import json
import sys
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hopframe.baseline import pointer, reencode
from hopframe.exec.session import GraphSession
from hopframe.measure.measures import Timing, bench, scaling, summary
from hopframe.paths import forms
from hopframe.workloads import extra, snb


def growth(spark: SparkSession, small: str, large: str, runs: int = 5, suite: dict[str, Callable] | None = None) -> dict:
    """Medians of the benchmark queries on two sizes, by class, and the growth of each with their median."""
    from hopframe.workloads.registry import SUITE_41

    found: list[dict[str, Timing]] = []
    for sf_dir in (small, large):
        found.append({})
        for name, run in (suite or SUITE_41).items():
            bench(lambda: run(spark, sf_dir), 1)  # noqa: B023  compiled code is not what is measured
            found[-1][name] = bench(lambda: run(spark, sf_dir), runs)  # noqa: B023
    return {"small": summary(found[0]), "large": summary(found[1]), "growth": {k: round(v, 2) for k, v in scaling(*found).items()}}


def flights(spark: SparkSession, sf_dir: str, runs: int = 5) -> dict:
    """Milliseconds of the flight queries with nothing cached, and over the cached table of legs."""
    g, out = GraphSession(spark, source=sf_dir), {}
    for name, w in snb.FLIGHTS.items():
        out[name] = {"cold": round(bench(lambda: g.cypher(w.text), runs, True, spark).median_ms)}  # noqa: B023
    held = g.table("events").cache()
    held.count()
    g.use("events", held)
    for name, w in snb.FLIGHTS.items():
        out[name]["cached"] = round(bench(lambda: g.cypher(w.text), runs).median_ms)  # noqa: B023
    held.unpersist()
    return out


def storage_forms(spark: SparkSession, sf_dir: str, seed: int, hops: tuple[int, ...] = (1, 2, 3), runs: int = 3, budget: int = 2_000_000) -> dict:
    """Milliseconds of counting walks from a seed: native tables, a node/edge copy, adjacency lists walked one by one."""
    g, out = GraphSession(spark, source=sf_dir), {}
    copy = reencode.reencode(g, ["TOUCHED"]).session
    lists = pointer.adjacency_lists(extra.touch(spark, sf_dir), budget)
    for n in hops:
        text = f"MATCH (a:Account {{id: {seed}}})-[:TOUCHED*{n}]->(c) RETURN count(*) AS n"
        out[n] = {"native": round(bench(lambda: g.cypher(text), runs).median_ms), "node_edge": round(bench(lambda: copy.cypher(text), runs).median_ms)}  # noqa: B023
        try:
            walked: list[int] = []

            def walk(n: int = n, walked: list[int] = walked) -> DataFrame:
                walked.append(pointer.pointer_walk(lists, [seed], n, budget))
                return spark.range(0)

            out[n]["per_tuple"] = round(bench(walk, 1).median_ms)
            out[n]["walks"] = walked[0]
        except pointer.OutOfBudget:
            out[n]["per_tuple"] = None
    return out


def memory_boundary(spark: SparkSession, sf_dir: str, budget: int = 2_000_000, most: int = 4) -> dict:
    """Hops at which walks over the whole graph leave the budget of one process, and how many walks Spark counts there."""
    lists = pointer.adjacency_lists(extra.touch(spark, sf_dir), budget)
    g = GraphSession(spark, source=sf_dir)
    for n in range(1, most + 1):
        try:
            pointer.pointer_walk(lists, list(lists), n, budget)
        except pointer.OutOfBudget:
            text = f"MATCH (a:Account)-[:TOUCHED*{n}]->(c) RETURN count(*) AS n"
            return {"hops": n, "budget": budget, "walks": g.cypher(text).first().n}
    return {"hops": None, "budget": budget}


def path_forms(spark: SparkSession, sf_dir: str, seed: int, runs: int = 3) -> dict:
    """Milliseconds of ranges 1..2 to 1..5 in every form on a sparse link, and of two forests by doubling and by levels."""
    link, start, out = extra.hot(spark, sf_dir), extra.seed(spark, seed), {}
    for hi in range(2, 6):
        out[f"1..{hi}"] = {f: round(bench(lambda: forms.ranged(link, 1, hi, f, seeds=start).groupBy("hops").count(), runs).median_ms) for f in ("unrolled", "shared", "frontier")}  # noqa: B023
        out[f"1..{hi}"]["recursive"] = round(bench(lambda: recursive(spark, link, seed, hi), runs).median_ms)  # noqa: B023
    part = spark.read.parquet(f"{sf_dir}/part.parquet")
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet")
    trees = {
        "component_of": (part.where("p_partkey > 0").select(F.col("p_partkey").alias("s0"), F.floor(F.col("p_partkey") / 10).alias("t0")), part.select(F.col("p_partkey").alias("s0")), 1),
        "reply_of": (turns.where("turn > 0").select(F.col("conv_id").alias("s0"), F.col("turn").alias("s1"), F.col("conv_id").alias("t0"), (F.col("turn") - 1).alias("t1")), turns.select(F.col("conv_id").alias("s0"), F.col("turn").alias("s1")), 2),
    }
    for name, (tree, seeds, keys) in trees.items():
        out[name] = {"doubling": round(bench(lambda: forms.doubling(tree, seeds, keys), runs).median_ms), "levels": round(bench(lambda: forms.reach(tree, seeds, keys, 0), runs).median_ms)}  # noqa: B023
    return out


def recursive(spark: SparkSession, link: DataFrame, seed: int, hi: int) -> DataFrame:
    """The bounded range as the engine's own recursive common table expression."""
    link.createOrReplaceTempView("hot_link")
    return spark.sql(f"""WITH RECURSIVE w(t0, hops, used) MAX RECURSION LEVEL {hi + 2} AS (SELECT t0, 1, array(e0) FROM hot_link WHERE s0 = {int(seed)}
        UNION ALL SELECT h.t0, hops + 1, array_append(used, h.e0) FROM w JOIN hot_link h ON w.t0 = h.s0 WHERE hops < {hi} AND NOT array_contains(used, h.e0))
        SELECT hops, count(*) AS n FROM w GROUP BY hops""")


def tax(spark: SparkSession, sf_dir: str, runs: int = 5) -> dict:
    """Milliseconds of the micro queries on native tables and on a node/edge copy, made before; counts must be equal."""
    g = GraphSession(spark, source=sf_dir)
    made = reencode.reencode(g, ["TOUCHED"])
    out = {}
    for name, w in snb.MICRO.items():
        native, copy = g.cypher(w.text), made.session.cypher(w.text)
        if native.collect() != copy.collect():
            raise AssertionError(f"{name}: the copy gives other counts")
        a, b = bench(lambda: g.cypher(w.text), runs), bench(lambda: made.session.cypher(w.text), runs)  # noqa: B023
        out[name] = {"native": round(a.median_ms), "copy": round(b.median_ms), "tax": round(b.median_ms / a.median_ms, 2)}
    return out


def main() -> None:
    small, large, runs = sys.argv[1], sys.argv[2], int(sys.argv[3]) if len(sys.argv) > 3 else 5
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name, run in {
        "tax": lambda: tax(spark, large, runs),
        "flights": lambda: flights(spark, large, runs),
        "storage forms": lambda: storage_forms(spark, large, 7, runs=runs),
        "memory boundary": lambda: memory_boundary(spark, small),
        "path forms": lambda: path_forms(spark, large, 103, runs),
        "growth": lambda: growth(spark, small, large, runs),
    }.items():
        print(json.dumps({name: run()}), flush=True)


if __name__ == "__main__":
    main()
