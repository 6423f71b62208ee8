"""Variable lengths against brute-force trails: bounds must not change what a relationship may do in one match."""

import random
from collections import Counter

import pytest

from hopframe.catalog.model import GraphMap
from hopframe.exec.session import GraphSession
from hopframe.plan.compile import PlanError

MAP = GraphMap.from_dict(
    {
        "graph": "tiny",
        "nodes": {"V": {"access": "own", "table": "v", "key": ["k"], "props": {"id": "k", "name": "name"}}},
        "edges": {
            "E": {"access": "separate", "table": "e", "edge_key": ["i"], "from": {"label": "V", "cols": ["a"]}, "to": {"label": "V", "cols": ["b"]}, "props": {"w": "w"}},
            "F": {"access": "separate", "table": "f", "edge_key": ["i", "j"], "from": {"label": "V", "cols": ["a"]}, "to": {"label": "V", "cols": ["b"]}, "props": {"w": "w"}},
        },
    }
)


def graph(spark, edges, nodes=6):
    """A session over edges (a, b, w), stored twice: under a single key and under a key of two parts."""
    g = GraphSession(spark, MAP)
    g.use("v", spark.createDataFrame([(k, f"v{k}") for k in range(nodes)], "k long, name string"))
    g.use("e", spark.createDataFrame([(i, a, b, w) for i, (a, b, w) in enumerate(edges)], "i long, a long, b long, w long"))
    g.use("f", spark.createDataFrame([(f"{i}|", None if i % 2 else "|", a, b, w) for i, (a, b, w) in enumerate(edges)], "i string, j string, a long, b long, w long"))
    return g


def steps(edges, both, w):
    out = [(a, b, i) for i, (a, b, x) in enumerate(edges) if w is None or x == w]
    return out + [(b, a, i) for a, b, i in out if a != b] if both else out


def walks(edges, starts, lo, hi, both=False, w=None):
    """(start, end, edges used) of all trails of ``lo`` to ``hi`` hops."""
    own, level, out = steps(edges, both, w), [(s, s, ()) for s in starts], []
    for n in range(hi + 1):
        out += level if n >= lo else []
        level = [(s, b, (*u, i)) for s, at, u in level for a, b, i in own if a == at and i not in u]
    return out


def rows(df):
    return Counter(tuple(r) for r in df.collect())


EDGES = {s: [(random.Random(s * 31 + i).randrange(6), random.Random(s * 17 + i + 5).randrange(6), random.Random(s + 7 * i).randrange(2)) for i in range(8)] for s in range(3)}


@pytest.mark.parametrize("seed", EDGES)
@pytest.mark.parametrize("kind", ["E", "F"])
@pytest.mark.parametrize("length, most", [("*1..6", 6), ("*1..7", 7), ("*", 9)])
def test_bounds_do_not_change_meaning(spark, seed, kind, length, most):
    edges = EDGES[seed]
    g = graph(spark, edges)
    found = walks(edges, range(6), 1, most)
    second = Counter((s, b) for s, at, u in found for a, b, i in steps(edges, False, None) if a == at and i not in u)
    assert rows(g.cypher(f"MATCH (a:V)-[:{kind}{length}]->(b)-[:{kind}]->(c) RETURN a.id AS a, c.id AS c")) == second
    if kind == "E":
        picked = Counter((s, t) for s, t, _ in walks(edges, range(6), 1, most, w=0))
        assert rows(g.cypher(f"MATCH (a:V)-[:E{length} {{w: 0}}]->(b) RETURN a.id AS a, b.id AS b")) == picked


@pytest.mark.parametrize("seed", EDGES)
@pytest.mark.parametrize("length, most", [("*1..2", 2), ("*1..4", 4), ("*1..7", 7), ("*", 9)])
@pytest.mark.parametrize("arrow, both", [("-", True), ("->", False)])
def test_distinct_ends_equal_trails(spark, seed, length, most, arrow, both):
    edges = EDGES[seed]
    g = graph(spark, edges)
    ends = {}
    for s, t, u in walks(edges, [0, 3], 1, most, both):
        ends[s, t] = min(len(u), ends.get((s, t), 99))
    where = "WHERE a.id IN [0, 3]"
    assert rows(g.cypher(f"MATCH (a:V)-[:E{length}]{arrow}(b) {where} RETURN DISTINCT a.id AS a, b.id AS b")) == Counter(list(ends))
    assert rows(g.cypher(f"MATCH p = (a:V)-[:F{length}]{arrow}(b) {where} RETURN a.id AS a, b.id AS b, min(length(p)) AS n")) == Counter((s, t, n) for (s, t), n in ends.items())


LINE = [(1, 2, 0), (2, 3, 1), (3, 4, 1)]
RING = [(1, 2, 0), (2, 1, 0)]
SHORTCUT = [(1, 2, 0), (2, 4, 0), (1, 4, 0)]
DIAMOND = [(1, 2, 0), (1, 3, 0), (2, 4, 0), (3, 4, 0)]


@pytest.mark.parametrize(
    "edges, query, want",
    [
        (RING, "MATCH (a:V {id: 1})-[:E*]->(b)-[:E]->(c) RETURN b.id AS b, c.id AS c", [(2, 1)]),
        (LINE, "MATCH (a:V {id: 1})-[:E* {w: 0}]->(b) RETURN b.id AS b", [(2,)]),
        (LINE, "MATCH (a:V {id: 1})-[:E*1..6 {w: 0}]->(b) RETURN b.id AS b", [(2,)]),
        (LINE, "MATCH (a:V {id: 1})-[:E*1..7 {w: 0}]->(b) RETURN b.id AS b", [(2,)]),
        (LINE, "MATCH p = shortestPath((a:V {id: 1})-[:E*1..15 {w: 0}]->(b:V {id: 4})) RETURN length(p) AS n", []),
        (LINE, "MATCH (a:V {id: 1})-[:E*1..2 {w: 0}]-(b) RETURN b.id AS b", [(2,)]),
        (SHORTCUT, "MATCH p = (a:V {id: 1})-[:E*]->(b) RETURN b.id AS b, max(length(p)) AS n", [(2, 1), (4, 2)]),
        (SHORTCUT, "MATCH p = (a:V {id: 1})-[:E*]->(b:V {id: 4}) RETURN DISTINCT b.id AS b, length(p) AS n", [(4, 1), (4, 2)]),
        (SHORTCUT, "MATCH p = (a:V {id: 1})-[:E*]->(b) WHERE length(p) > 1 RETURN DISTINCT b.id AS b", [(4,)]),
        (LINE[:1], "MATCH (a:V {id: 1})-[:E*1..7]-(b) RETURN DISTINCT b.id AS b", [(2,)]),
        (DIAMOND, "MATCH p = allShortestPaths((a:V {id: 1})-[:E*]->(b:V {id: 4})) RETURN length(p) AS n", [(2,), (2,)]),
        (DIAMOND, "MATCH p = shortestPath((a:V {id: 1})-[:E*]->(b:V {id: 4})) RETURN length(p) AS n, nodes(p) AS ns", [(2, [1, 2, 4])]),
        (DIAMOND, "MATCH p = allShortestPaths((a:V {id: 1})-[:E*]-(b:V {id: 4})) RETURN nodes(p) AS ns", [([1, 2, 4],), ([1, 3, 4],)]),
        (LINE, "MATCH p = (a:V {id: 1})-[:E*]->(b:V {id: 4}) RETURN nodes(p) AS ns", [([1, 2, 3, 4],)]),
        (LINE, "MATCH p = (b:V {id: 4})<-[:E*1..9]-(a:V {id: 1}) RETURN nodes(p) AS ns", [([4, 3, 2, 1],)]),
        (LINE, "MATCH p = (a:V)-[:E]->(m)-[:E*1..9]->(b:V {id: 4}) WHERE a.id = 1 RETURN nodes(p) AS ns", [([1, 2, 3, 4],)]),
        (RING, "MATCH (a:V {id: 1}) WHERE COUNT { (a)-[:E*]->(b) } = 2 RETURN DISTINCT a.id AS a", [(1,)]),
        (DIAMOND, "MATCH (a:V {id: 1})-[:E*]->(b) RETURN DISTINCT b.id AS b, count(*) AS n", [(2, 1), (3, 1), (4, 2)]),
        (LINE, "MATCH (a:V {id: 1}), (b:V {id: 4}) MATCH p = shortestPath((a)-[:E*]-(b)) RETURN length(p) AS n", [(3,)]),
        (LINE, "MATCH (v0:V {id: 2}) WITH v0 AS v1 WITH v1 AS v2 WITH v2 AS v3 WITH v3 AS v4 WITH v4 AS v5 WITH v5 AS v6 RETURN v6.name AS n", [("v2",)]),
        (LINE, "MATCH (a:V {id: 1})-[:E* WHERE 1 = 1]->(b) RETURN b.id AS b", [(2,), (3,), (4,)]),
    ],
)
def test_paths_by_hand(spark, edges, query, want):
    got = graph(spark, edges).cypher(query).collect()
    assert sorted(tuple(r) for r in got) == sorted(want)


def test_bounds_of_slices_may_be_computed(spark):
    got = graph(spark, LINE).cypher("UNWIND [0, 1, 2, -1] AS k RETURN k, [1, 2, 3, 4, 5][k..4] AS a, [1, 2, 3][..k] AS b")
    assert {r.k: (r.a, r.b) for r in got.collect()} == {k: ([1, 2, 3, 4, 5][k:4], [1, 2, 3][:k]) for k in (0, 1, 2, -1)}


def test_unknown_property_is_null_and_a_lost_one_an_error(spark):
    g = graph(spark, LINE)
    assert g.cypher("MATCH (a:V {id: 1}) RETURN a.nothing AS n").first().n is None
    compiler, _ = g.compiled("MATCH (a:V {id: 1}) RETURN a.name AS n")
    from hopframe.lang import ast as A
    from hopframe.plan.compile import NodeB, Scope

    with pytest.raises(PlanError):
        compiler.expr(A.Prop(A.Var("a"), "name"), Scope(None, {"a": NodeB(("a__k0",), {}, ("V",))}))


def test_operators_go_by_column_types(spark):
    g = graph(spark, LINE)
    g.use("v", spark.createDataFrame([(7, "x")], "k long, name string"))
    text = GraphMap.from_dict({"graph": "t", "nodes": {"V": {"access": "own", "table": "v", "key": ["k"], "props": {"id": "k", "tag": "name"}}}, "edges": {}})
    h = GraphSession(spark, text)
    h.use("v", g.table("v"))
    row = h.cypher("MATCH (a:V) WHERE a.tag + a.tag = 'xx' WITH a, a.id AS n, a.tag AS t RETURN n / 4 AS q, a.id / 2 AS p, t + a.tag AS s, (n + 1) / 3 AS r, a.id / 2.0 AS d").first()
    assert (row.q, row.p, row.s, row.r, row.d) == (1, 3, "xx", 2, 3.5)
