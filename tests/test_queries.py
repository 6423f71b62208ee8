"""Every registered query of the library against its hand-written SQL."""

import pytest

from hopframe.measure.measures import parity
from hopframe.workloads.registry import ORACLES, QUERIES

SF = "sf0.001"


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(spark, duck, name):
    got = QUERIES[name](spark, f"/root/testdata/{SF}")
    relation = duck(SF).execute(ORACLES[name])
    names = [d[0] for d in relation.description]
    rows = [tuple(tuple(v) if isinstance(v, list) else v for v in r) for r in relation.fetchall()]
    assert parity(got, (names, rows))


def test_every_query_has_sql():
    assert set(QUERIES) == set(ORACLES)
