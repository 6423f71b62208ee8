import pytest

from hopframe.paths import forms


@pytest.fixture(scope="module")
def chain(spark):
    return spark.createDataFrame([(i, i + 1, i, 1.0) for i in range(5)], "s0 long, t0 long, e0 long, w double")


@pytest.mark.parametrize("weight", [None, "w"])
def test_shortest_ends_early_with_an_error_only(spark, chain, weight):
    source, target = spark.createDataFrame([(0,)], "s0 long"), spark.createDataFrame([(5,)], "t0 long")
    assert [r.cost for r in forms.shortest(chain, source, target, weight, max_rounds=5).collect()] == [5.0]
    with pytest.raises(forms.PathLimit):
        forms.shortest(chain, source, target, weight, max_rounds=4)


def test_reach_ends_early_with_an_error_only(spark, chain, monkeypatch):
    source = spark.createDataFrame([(0,)], "s0 long")
    monkeypatch.setattr(forms, "REACH_ROUNDS", 5)
    assert forms.frontier(chain, source).count() == 5
    monkeypatch.setattr(forms, "REACH_ROUNDS", 4)
    with pytest.raises(forms.PathLimit):
        forms.frontier(chain, source)
    assert forms.frontier(chain, source, hi=4).count() == 4
