import pytest
from pyspark.sql import functions as F

from hopframe.baseline import pointer
from hopframe.measure import experiments
from hopframe.paths import forms
from hopframe.workloads import extra
from hopframe.workloads.registry import SUITE_41

DATA = "/root/testdata/sf0.001"


def test_tax_is_of_equal_counts(spark):
    found = experiments.tax(spark, DATA, 1)
    assert set(found) == {"tax_2hop_seed", "tax_3hop_seed", "tax_2hop_all"} and all(v["tax"] > 0 for v in found.values())


def test_boundary_and_storage_forms(spark):
    lists = pointer.adjacency_lists(extra.touch(spark, DATA), 2_000)
    found = experiments.memory_boundary(spark, DATA, 5_000, 3)
    assert found == {"hops": 2, "budget": 5_000, "walks": pointer.pointer_walk(lists, list(lists), 2)}
    told = experiments.storage_forms(spark, DATA, 7, (1, 2), 1, 2_000)
    assert told[1]["walks"] > 0 and all(told[n]["native"] > 0 for n in told)


def test_growth_tells_each_query_and_the_median(spark):
    found = experiments.growth(spark, DATA, DATA, 1, {k: SUITE_41[k] for k in ("is1", "is4", "bi6")})
    assert set(found["growth"]) == {"is1", "is4", "bi6", "median"}


@pytest.mark.parametrize("hi", [None, 9])
def test_between_meets_in_the_middle(spark, hi):
    edges = [(i, i + 1) for i in range(8)] + [(20, 21)]
    link = spark.createDataFrame([(a, b, k) for k, (a, b) in enumerate(edges)], "s0 long, t0 long, e0 long")
    pairs = spark.createDataFrame([(0, 8), (2, 3), (3, 2), (20, 4), (5, 5)], "s0 long, t0 long")
    assert {(r.s0, r.t0): r.hops for r in forms.between(link, pairs, hi=hi).collect()} == {(0, 8): 8, (2, 3): 1, (5, 5): 0}
    assert (0, 8) not in {(r.s0, r.t0) for r in forms.between(link, pairs, hi=7).collect()}


def test_ancestors_by_walking_and_by_doubling(spark, monkeypatch):
    chain = spark.range(1, 60).select(F.col("id").alias("s0"), (F.col("id") - 1).alias("t0"))
    seeds = spark.createDataFrame([(59,), (3,)], "s0 long")
    want = sorted([(59, t, 59 - t) for t in range(60)] + [(3, t, 3 - t) for t in range(4)])
    assert sorted((r.s0, r.t0, r.hops) for r in forms.ancestors(chain, seeds).collect()) == want
    monkeypatch.setattr(forms, "SMALL_ROWS", 0)
    assert sorted((r.s0, r.t0, r.hops) for r in forms.ancestors(chain, seeds).collect()) == want
    assert {r.hops for r in forms.ancestors(chain, seeds, lo=2, hi=4).collect()} == {2, 3, 4}
