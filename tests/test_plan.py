"""Classification, plan shape, structure of the code, and catalog tools."""

import ast
from itertools import permutations
from pathlib import Path

import pytest

from hopframe.baseline.reencode import reencode, uncoupled
from hopframe.catalog import GraphMap
from hopframe.catalog.discover import propose
from hopframe.catalog.model import EdgeAccess, EdgeMap, End, NodeAccess, NodeMap
from hopframe.catalog.validate import validate
from hopframe.exec.session import GraphSession
from hopframe.graphopt.order import cost_of, order_joins
from hopframe.measure.measures import parity, plan_shape
from hopframe.plan.profile import Strategy, classify_hop

ROOT = Path(__file__).parent.parent / "hopframe"


def test_every_combination_has_one_strategy():
    seen = set()
    for left in NodeAccess:
        for right in NodeAccess:
            for access in EdgeAccess:
                nodes = {"L": NodeMap("L", left, ("k",), "t"), "R": NodeMap("R", right, ("k",), "u")}
                gmap = GraphMap("m", nodes, {})
                edge = EdgeMap("E", access, End("L", ("a",)), End("R", ("b",)), "e", "L" if access is EdgeAccess.KEY else None, name="E")
                for backwards in (False, True):
                    for shared in (False, True):
                        prev = classify_hop("L", edge, "R", gmap) if shared else None
                        profile = classify_hop("L", edge, "R", gmap, backwards, prev)
                        assert isinstance(profile.strategy, Strategy)
                        assert (profile.left_access, profile.edge_access, profile.right_access) == (left, access, right)
                        seen.add(profile.strategy)
    assert seen == set(Strategy) - {Strategy.SHARED_ROW}


def test_shared_row_needs_a_declaration():
    g = GraphMap.commerce()
    first = classify_hop("Order", g.edges["CONTAINS"], "Part", g)
    assert classify_hop("Part", g.edges["SOURCED_FROM"], "Supplier", g, False, first).strategy is Strategy.SHARED_ROW
    free = uncoupled(g)
    assert classify_hop("Part", free.edges["SOURCED_FROM"], "Supplier", free, False, first).strategy is Strategy.TRIPLE_JOIN


#: raw schema flags may be read in these modules only, so often at most
RATCHET = {"plan/compile.py": 21, "exec/session.py": 2}


def test_ratchet_on_raw_flags():
    counts = {}
    for path in ROOT.rglob("*.py"):
        name = str(path.relative_to(ROOT))
        if name.startswith(("catalog/", "plan/profile.py", "baseline/", "llm/", "sources/")):
            continue
        hits = sum(isinstance(x, ast.Attribute) and x.attr in ("access", "type_column", "same_row_as", "owner", "single_parent") for x in ast.walk(ast.parse(path.read_text())))
        if hits:
            counts[name] = hits
    assert set(counts) <= set(RATCHET), counts
    for name, most in RATCHET.items():
        assert counts.get(name, 0) <= most, counts


def test_library_does_not_import_llm():
    for path in ROOT.rglob("*.py"):
        if "llm" not in path.parts:
            assert "hopframe.llm" not in path.read_text(), path


def test_joins_of_each_strategy(spark):
    g = GraphSession(spark, source="/root/testdata/sf0.001")

    def joins(q):
        return plan_shape(g.cypher(q))["joins"]

    assert joins("MATCH (a:Account)-[:TOUCHED]->(b) RETURN a.id AS a, b.id AS b") == 0
    for h in (2, 3, 4):
        assert joins(f"MATCH (a:Account)-[:HOT_CLICK*{h}]->(b) RETURN a.id AS a, b.id AS b") == h - 1
    assert joins("MATCH (c:Customer)-[:PLACED]->(o:Order) RETURN c.id AS c, o.total AS t") == 0
    assert joins("MATCH (c:Customer)-[:PLACED]->(o:Order) RETURN c.name AS c, o.total AS t") == 1
    assert joins("MATCH (o:Order)-[:CONTAINS]->(p:Part) RETURN o.total AS o, p.name AS p") == 2


def test_filters_reach_the_scan(spark):
    g = GraphSession(spark, source="/root/testdata/sf0.001")
    plan = g.cypher("MATCH (c:Customer {segment: 'BUILDING'})-[:PLACED]->(o:Order) WHERE o.total > 1000 RETURN c.name AS n, o.id AS o")._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(c_mktsegment,BUILDING)" in plan and "GreaterThan(o_totalprice" in plan


def test_validation(spark):
    g = GraphSession(spark, source="/root/testdata/sf0.001")
    found = validate(g, deep=True)
    kinds = {(f.kind, f.entry) for f in found}
    assert ("several endpoint labels", "TAGGED") in kinds
    assert ("repeated rows of a keyless link", "CONTAINS") in kinds or not any(k == "missing column" for k, _ in kinds)
    assert not any(f.kind in ("missing column", "repeated key", "edge without its node") for f in found)
    broken = GraphSession(spark, g.gmap.with_edge("TOUCHED", props={"x": "nope"}), g.source)
    assert any(f.kind == "missing column" and f.entry == "TOUCHED" for f in validate(broken))


def test_yaml_round_trip():
    import yaml

    g = GraphMap.commerce()
    assert GraphMap.from_dict(yaml.safe_load(g.to_yaml())) == g
    with pytest.raises(ValueError):
        GraphMap.from_dict({"nodes": {}, "edges": {"E": {"access": "separate", "table": "t", "from": {"label": "A", "cols": ["x"]}, "to": {"label": "A", "cols": ["y"]}}}})


def test_discovery(spark):
    tables = {t: spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("customer", "orders", "nation", "region")}
    draft = propose(tables)
    assert draft.keys["customer"] == ["c_custkey"] and draft.keys["orders"] == ["o_orderkey"]
    assert ("orders", "o_custkey", "customer", "c_custkey") in {x[:4] for x in draft.links}
    assert any(t == "orders" and c == "o_orderstatus" for t, c, _ in draft.discriminators)
    assert "ORDERS" in draft.to_dict()["edges"]["O_CUSTKEY_TO_CUSTOMER"]["owner"].upper()


@pytest.mark.parametrize("how", [{"blob": "json"}, {"blob": "map"}, {"layout": "per_label"}])
def test_reencoded_equals_native(spark, how):
    g = GraphSession(spark, source="/root/testdata/sf0.001")
    copy = reencode(g, ["TOUCHED"], **how)
    for q in ("MATCH (a:Account {id: 7})-[:TOUCHED]->(b)-[:TOUCHED]->(c) RETURN c.id AS c, count(*) AS n", "MATCH (a:Account)-[r:TOUCHED]->(b) WHERE r.value > 100 RETURN b.id AS b, max(r.value) AS m"):
        assert parity(g.cypher(q), copy.session.cypher(q))


def test_naive_shared_row_is_wrong(spark):
    q = "MATCH (o:Order)-[:CONTAINS]->(p:Part)-[:SOURCED_FROM]->(s:Supplier) RETURN count(*) AS n"
    g = GraphSession(spark, source="/root/testdata/sf0.001")
    assert g.cypher(q).first().n == 6000
    assert GraphSession(spark, uncoupled(g.gmap), g.source).cypher(q).first().n > 100_000


def test_join_order_is_the_cheapest():
    rows = {"a": 1000.0, "b": 10.0, "c": 5000.0, "d": 200.0, "e": 3.0}
    links = {frozenset("ab"): 0.1, frozenset("bc"): 0.001, frozenset("cd"): 0.005, frozenset("ae"): 0.5, frozenset("de"): 0.3}
    for keep in ({}, {"a": 0.01}, {"c": 0.1, "e": 0.5}):
        kept = {n: r * keep.get(n, 1.0) for n, r in rows.items()}
        linked = [o for o in permutations(kept) if all(any(frozenset({x, y}) in links for x in o[:k]) for k, y in enumerate(o) if k)]
        assert cost_of(order_joins(kept, links), kept, links) == pytest.approx(min(cost_of(list(o), kept, links) for o in linked))
    assert set(order_joins({"a": 1.0, "b": 2.0, "c": 3.0}, {frozenset("bc"): 0.1})) == {"a", "b", "c"}
