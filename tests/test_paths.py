"""Path loops, factorized counts and triangles against brute force; baselines and their budgets."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from hopframe.baseline import algos
from hopframe.baseline.pointer import OutOfBudget, adjacency_lists, pointer_walk
from hopframe.graphopt import factor, triangles
from hopframe.measure.measures import Timing, bench, ratio, scaling, summary
from hopframe.paths import forms


def random_edges(seed, n=9, m=24):
    draw = random.Random(seed)
    return [(draw.randrange(n), draw.randrange(n)) for _ in range(m)]


def link(spark, edges):
    return spark.createDataFrame([(a, b, k) for k, (a, b) in enumerate(edges)], "s0 long, t0 long, e0 long")


def seeds(spark, *ids):
    return spark.createDataFrame([(i,) for i in ids], "s0 long")


def walks(edges, starts, hops):
    level = [(s, s, ()) for s in starts]
    for _ in range(hops):
        level = [(s, b, (*u, k)) for s, at, u in level for k, (a, b) in enumerate(edges) if a == at and k not in u]
    return level


@pytest.mark.parametrize("seed", [1, 2])
def test_forms_agree(spark, seed):
    edges = random_edges(seed, m=14)
    want = sorted((s, t, n) for n in (1, 2, 3) for s, t, _ in walks(edges, {a for a, _ in edges}, n))
    for form in ("unrolled", "shared", "frontier"):
        got = forms.ranged(link(spark, edges), 1, 3, form)
        assert sorted((r.s0, r.t0, r.hops) for r in got.collect()) == want, form


@pytest.mark.parametrize("seed", [3, 4])
def test_reach_and_shortest(spark, seed):
    edges = random_edges(seed)
    dist, level = {0: 0}, {0}
    while level:
        level = {b for a, b in edges if a in level} - set(dist)
        dist |= {x: max(dist.values()) + 1 for x in level}
    got = forms.frontier(link(spark, edges), seeds(spark, 0), lo=0)
    assert {r.t0: r.hops for r in got.collect()} == dist
    back = forms.shortest(link(spark, edges), seeds(spark, 0), spark.range(9).select(F.col("id").alias("t0")))
    assert {r.t0: r.cost for r in back.collect()} == dist
    on_cycle = 0 in {b for _, b, _ in itertools.chain.from_iterable(walks(edges, [0], n) for n in range(1, 6))}
    from_one = {r.t0 for r in forms.frontier(link(spark, edges), seeds(spark, 0), lo=1).collect()}
    assert (0 in from_one) == on_cycle and from_one - {0} == set(dist) - {0}


def test_weighted_shortest(spark):
    df = spark.createDataFrame([(0, 1, 0, 5.0), (0, 2, 1, 1.0), (2, 1, 2, 1.5), (1, 3, 3, 1.0)], "s0 long, t0 long, e0 long, w double")
    got = forms.shortest(df, seeds(spark, 0), spark.createDataFrame([(1,), (3,), (9,)], "t0 long"), "w")
    assert {r.t0: r.cost for r in got.collect()} == {1: 2.5, 3: 3.5}


def test_doubling_equals_walking_up(spark):
    parents = {i: i // 3 for i in range(1, 60)}
    df = spark.createDataFrame([(a, b) for a, b in parents.items()], "s0 long, t0 long")
    want = set()
    for i in range(60):
        at, h = i, 0
        want.add((i, at, h))
        while at in parents:
            at, h = parents[at], h + 1
            want.add((i, at, h))
    got = forms.doubling(df, spark.range(60).select(F.col("id").alias("s0")))
    assert {(r.s0, r.t0, r.hops) for r in got.collect()} == want
    with pytest.raises(forms.PathLimit):
        forms.doubling(spark.createDataFrame([(1, 2), (2, 1)], "s0 long, t0 long"), seeds(spark, 1))


@pytest.mark.parametrize("seed", [5, 6])
def test_factorized_counts(spark, seed):
    edges = random_edges(seed)
    df = link(spark, edges)
    assert factor.two_hop_count(df).first().n == len(walks(edges, {a for a, _ in edges}, 2))
    assert factor.two_hop_count(df, seeds(spark, 0)).first().n == len(walks(edges, [0], 2))
    assert factor.three_hop_count(df, seeds(spark, 0)).first().n == len(walks(edges, [0], 3))


@pytest.mark.parametrize("seed", [7, 8])
def test_triangles(spark, seed):
    edges = random_edges(seed, m=40)
    pairs = {tuple(sorted(e)) for e in edges if e[0] != e[1]}
    want = sorted(t for t in itertools.combinations(range(9), 3) if all(p in pairs for p in itertools.combinations(t, 2)))
    assert sorted(tuple(r) for r in triangles.undirected_triangles(link(spark, edges)).collect()) == want
    arcs = set(edges)
    cycles = sorted((a, b, c) for a, b, c in itertools.permutations(range(9), 3) if a < b and a < c and {(a, b), (b, c), (c, a)} <= arcs)
    assert sorted(tuple(r) for r in triangles.directed_triangles(link(spark, edges)).collect()) == cycles


def test_pointer_walk_and_budget(spark):
    edges = random_edges(9)
    lists = adjacency_lists(link(spark, edges), 100)
    assert pointer_walk(lists, [0], 3) == len(walks(edges, [0], 3))
    with pytest.raises(OutOfBudget):
        adjacency_lists(link(spark, edges), 10)
    with pytest.raises(OutOfBudget):
        pointer_walk(lists, list(range(9)), 6, budget=50)


def test_components_and_pagerank(spark):
    df = link(spark, [(1, 2), (3, 2), (5, 6), (7, 7)])
    assert {r.node: r.component for r in algos.wcc(df).collect()} == {1: 1, 2: 1, 3: 1, 5: 5, 6: 5, 7: 7}
    ranks = {r.node: r.rank for r in algos.pagerank(link(spark, [(1, 2), (2, 1)]), rounds=5).collect()}
    assert ranks == pytest.approx({1: 0.5, 2: 0.5})


def test_adjacency_parts(spark):
    df = spark.range(1000).select(F.lit(1).cast("long").alias("s0"), F.col("id").alias("t0"), F.col("id").alias("e0"))
    parts = forms.adjacency(df, chunk=100).select(F.size("out").alias("n")).collect()
    assert sum(r.n for r in parts) == 1000 and len(parts) > 5


def test_measures(spark):
    t = bench(lambda: spark.range(3), runs=3)
    assert len(t.seconds) == 3 and t.median_ms > 0
    a, b = {"is1": Timing((1.0,)), "bi1": Timing((2.0,))}, {"is1": Timing((2.0,)), "bi1": Timing((8.0,))}
    assert scaling(a, b) == {"is1": 2.0, "bi1": 4.0, "median": 3.0}
    assert summary(a)["is"]["median"] == 1000.0 and ratio(b["bi1"], a["bi1"]) == 4.0
