"""The query language on small graphs, against brute force, and its three back ends against each other."""

import itertools

import pytest

from hopframe.catalog import GraphMap
from hopframe.emit.sqltext import Dialect, to_sql
from hopframe.exec.session import GraphSession
from hopframe.lang.parser import QuerySyntaxError, ReadOnlyError, parse
from hopframe.plan.compile import PlanError

MAP = {
    "graph": "small",
    "nodes": {"N": {"access": "own", "table": "small_nodes", "key": ["id"], "props": {"id": "id", "v": "v"}}},
    "edges": {"E": {"access": "separate", "table": "small_edges", "edge_key": ["eid"], "from": {"label": "N", "cols": ["a"]}, "to": {"label": "N", "cols": ["b"]}, "props": {"w": "w"}}},
}
GRAPHS = {
    "line5": [(1, 2), (2, 3), (3, 4), (4, 5)],
    "cycle3": [(1, 2), (2, 3), (3, 1)],
    "loop": [(1, 1), (1, 2)],
    "parallel": [(1, 2), (1, 2), (2, 1)],
    "diamond": [(1, 2), (1, 3), (2, 4), (3, 4)],
    "hub": [(1, i) for i in range(2, 9)] + [(i, 9) for i in range(2, 9)],
    "empty": [],
}


def session(spark, edges, nodes=None):
    g = GraphSession(spark, GraphMap.from_dict(MAP))
    ids = nodes or sorted({x for e in edges for x in e} | {1})
    g.use("small_nodes", spark.createDataFrame([(i, None if i == 3 else i * 10) for i in ids], "id long, v long"))
    g.use("small_edges", spark.createDataFrame([(k, a, b, float(k)) for k, (a, b) in enumerate(edges)], "eid long, a long, b long, w double"))
    return g


def trails(edges, start, lo, hi, both=False):
    """Ends of all edge-unique walks of lo to hi edges from a node."""
    steps = [(k, a, b) for k, (a, b) in enumerate(edges)] + ([(k, b, a) for k, (a, b) in enumerate(edges) if a != b] if both else [])
    out, level = ([start] if lo == 0 else []), [(start, ())]
    for depth in range(1, hi + 1):
        level = [(b, (*used, k)) for at, used in level for k, a, b in steps if a == at and k not in used]
        if depth >= lo:
            out += [at for at, _ in level]
    return sorted(out)


@pytest.mark.parametrize("name", GRAPHS)
@pytest.mark.parametrize(("lo", "hi"), [(1, 1), (2, 2), (1, 3), (0, 2)])
@pytest.mark.parametrize("arrow", ["->", "-"])
def test_paths_are_trails(spark, name, lo, hi, arrow):
    edges = GRAPHS[name]
    got = session(spark, edges).cypher(f"MATCH (a:N {{id: 1}})-[:E*{lo}..{hi}]{arrow}(b:N) RETURN b.id AS b")
    assert sorted(r.b for r in got.collect()) == trails(edges, 1, lo, hi, arrow == "-")


@pytest.mark.parametrize("name", [n for n in GRAPHS if n != "hub"])
def test_open_paths(spark, name):
    edges = GRAPHS[name]
    g = session(spark, edges)
    every = trails(edges, 1, 1, len(edges) + 1)
    assert sorted(r.b for r in g.cypher("MATCH (a:N {id: 1})-[:E*]->(b:N) RETURN b.id AS b").collect()) == every
    assert sorted(r.b for r in g.cypher("MATCH (a:N {id: 1})-[:E*]->(b:N) RETURN DISTINCT b.id AS b").collect()) == sorted(set(every))


@pytest.mark.parametrize("name", GRAPHS)
def test_two_hops_do_not_reuse_an_edge(spark, name):
    edges = GRAPHS[name]
    got = session(spark, edges).cypher("MATCH (a:N)-[x:E]-(b:N)-[y:E]-(c:N) RETURN a.id AS a, c.id AS c")
    steps = [(k, a, b) for k, (a, b) in enumerate(edges)] + [(k, b, a) for k, (a, b) in enumerate(edges) if a != b]
    want = sorted((p[1], q[2]) for p, q in itertools.product(steps, steps) if p[2] == q[1] and p[0] != q[0])
    assert sorted((r.a, r.c) for r in got.collect()) == want


SCENARIOS = [
    ("MATCH (n:N) WHERE n.v > 10 RETURN n.id AS id", [(2,), (4,)]),
    ("MATCH (n:N) WHERE n.v IS NULL RETURN n.id AS id", [(3,)]),
    ("MATCH (n:N) WHERE NOT n.v > 10 RETURN n.id AS id", [(1,)]),
    ("MATCH (n:N) WHERE n.v = 10 OR n.v = 40 RETURN n.id AS id", [(1,), (4,)]),
    ("MATCH (n:N) WHERE n.id IN [1, 4, 9] RETURN n.id AS id", [(1,), (4,)]),
    ("MATCH (n:N) WHERE 1 < n.id <= 3 RETURN n.id AS id", [(2,), (3,)]),
    ("MATCH (n:N) RETURN count(*) AS c, count(n.v) AS v, sum(n.v) AS s", [(4, 3, 70)]),
    ("MATCH (n:N) WHERE n.id > 99 RETURN count(*) AS c, sum(n.v) AS s", [(0, 0)]),
    ("MATCH (n:N) RETURN n.id AS id ORDER BY n.v DESC SKIP 1 LIMIT 2", [(4,), (2,)]),
    ("MATCH (n:N) RETURN n.v AS v ORDER BY v LIMIT 4", [(10,), (20,), (40,), (None,)]),
    ("MATCH (a:N {id: 1}) OPTIONAL MATCH (a)-[:E]->(b:N) WHERE b.id > 50 RETURN a.id AS a, b.id AS b", [(1, None)]),
    ("MATCH (a:N) OPTIONAL MATCH (a)-[:E]->(b:N) RETURN a.id AS a, count(b) AS n", [(1, 2), (2, 1), (3, 1), (4, 0)]),
    ("MATCH (a:N) WHERE (a)-[:E]->() RETURN a.id AS a", [(1,), (2,), (3,)]),
    ("MATCH (a:N) WHERE NOT (a)-[:E]->() RETURN a.id AS a", [(4,)]),
    ("MATCH (a:N) WHERE EXISTS { (a)-[:E]->(b:N) WHERE b.id = 4 } RETURN a.id AS a", [(2,), (3,)]),
    ("MATCH (a:N) RETURN a.id AS a, COUNT { (a)-[:E]->() } AS n", [(1, 2), (2, 1), (3, 1), (4, 0)]),
    ("MATCH (a:N {id: 1})-[:E]->(b:N) WITH collect(b) AS bs UNWIND bs AS b MATCH (b)-[:E]->(c:N) RETURN b.id AS b, c.id AS c", [(2, 4), (3, 4)]),
    ("UNWIND [1, 2, 3] AS x RETURN x * 2 AS y", [(2,), (4,), (6,)]),
    ("UNWIND range(1, 3) AS x WITH x WHERE x <> 2 RETURN sum(x) AS s", [(4,)]),
    ("MATCH (n:N {id: 1}) RETURN 1 AS x UNION ALL MATCH (n:N {id: 2}) RETURN 1 AS x", [(1,), (1,)]),
    ("MATCH (n:N {id: 1}) RETURN 1 AS x UNION MATCH (n:N {id: 2}) RETURN 1 AS x", [(1,)]),
    ("MATCH (a:N) CALL { WITH a MATCH (a)-[:E]->(b:N) RETURN count(b) AS n } RETURN a.id AS a, n", [(1, 2), (2, 1), (3, 1), (4, 0)]),
    ("MATCH (a:N {id: 1}) CALL { WITH a MATCH (a)-[:E]->(b:N) RETURN b.id AS x UNION ALL WITH a RETURN a.id AS x } RETURN x", [(1,), (2,), (3,)]),
    ("MATCH p = (a:N {id: 1})-[:E*2]->(b:N) RETURN length(p) AS l, nodes(p) AS ns", [(2, [1, 2, 4]), (2, [1, 3, 4])]),
    ("MATCH p = shortestPath((a:N {id: 1})-[:E*]->(b:N {id: 4})) RETURN length(p) AS l", [(2,)]),
    ("MATCH (a:N {id: 4}), (b:N {id: 1}) OPTIONAL MATCH p = shortestPath((a)-[:E*]->(b)) RETURN coalesce(length(p), -1) AS l", [(-1,)]),
    ("MATCH (a:N)-[r:E]->(b:N) WHERE r.w >= 2 RETURN type(r) AS t, labels(a)[0] AS l, count(*) AS n", [("E", "N", 2)]),
    ("RETURN 7 / 2 AS i, 7.0 / 2 AS f, 7 % 4 AS m, 2 ^ 3 AS p, 1 / 0 AS z", [(3, 3.5, 3, 8.0, None)]),
    ("RETURN CASE WHEN 1 = 1 THEN 'a' ELSE 'b' END AS x, CASE 3 WHEN 2 THEN 'p' WHEN 3 THEN 'q' END AS y", [("a", "q")]),
    ("RETURN [x IN [1, 2, 3, 4] WHERE x % 2 = 0 | x * 10] AS l, [1, 2, 3][-1] AS last, [1, 2, 3][1..2] AS mid, size([1, 2]) AS n", [([20, 40], 3, [2], 2)]),
    ("RETURN any(x IN [1, 2] WHERE x > 1) AS a, all(x IN [1, 2] WHERE x > 1) AS b, none(x IN [1, 2] WHERE x > 5) AS c, single(x IN [1, 2] WHERE x = 2) AS d", [(True, False, True, True)]),
    ("RETURN reduce(s = 0, x IN [1, 2, 3] | s + x) AS s, head([5, 6]) AS h, last([5, 6]) AS l", [(6, 5, 6)]),
    ("RETURN 'abc' STARTS WITH 'ab' AS a, 'abc' ENDS WITH 'bc' AS b, 'abc' CONTAINS 'x' AS c, 'abc' =~ 'a.c' AS d, 'ab' + 'c' AS e, substring('hello', 1, 3) AS f", [(True, True, False, True, "abc", "ell")]),
    ("RETURN toInteger('12') AS a, toInteger('x') AS b, toFloat('1.5') AS c, toString(5) AS d, toUpper('a') AS e", [(12, None, 1.5, "5", "A")]),
    ("RETURN true XOR false AS a, null IS NULL AS b, coalesce(null, 3) AS c", [(True, True, 3)]),
    ("MATCH (n:N) WITH n.v > 15 AS big, count(*) AS c RETURN big, c", [(False, 1), (None, 1), (True, 2)]),
    ("MATCH (n:N) RETURN DISTINCT n.v IS NULL AS x", [(False,), (True,)]),
]


@pytest.mark.parametrize(("text", "want"), SCENARIOS)
def test_scenarios(spark, text, want):
    g = session(spark, GRAPHS["diamond"])

    def plain(rows):
        return sorted((tuple(list(v) if isinstance(v, list | tuple) else v for v in r) for r in rows), key=repr)

    assert plain(g.cypher(text).collect()) == plain(want)
    assert plain(g.sql(text).collect()) == plain(want)


@pytest.mark.parametrize("text", ["CREATE (a)", "MATCH (a) SET a.x = 1", "MATCH (a) DELETE a", "MERGE (a:N)", "MATCH (a) DETACH DELETE a", "MATCH (a) REMOVE a.x"])
def test_writes_are_refused(text):
    with pytest.raises(ReadOnlyError):
        parse(text)


@pytest.mark.parametrize("text", ["MATCH (a RETURN a", "RETURN", "MATCH (a) RETURN a.", "FOO"])
def test_bad_text(text):
    with pytest.raises(QuerySyntaxError):
        parse(text)


def test_unknown_names(spark):
    g = session(spark, GRAPHS["line5"])
    for text in ("MATCH (a:Nope) RETURN a", "MATCH (a)-[:NOPE]->(b) RETURN a", "MATCH (a:N) RETURN b", "RETURN $p AS x"):
        with pytest.raises((PlanError, ValueError)):
            g.cypher(text)


def test_parameters(spark):
    g = session(spark, GRAPHS["diamond"])
    assert [r.id for r in g.cypher("MATCH (n:N) WHERE n.id IN $ids AND n.v = $v RETURN n.id AS id", ids=[1, 2], v=20).collect()] == [2]
    assert g.cypher("RETURN $s AS s", s="it's \\ \"x\"").first().s == "it's \\ \"x\""


def test_three_back_ends_agree(spark, duck):
    from hopframe.measure.measures import parity
    from hopframe.workloads.patterns import PATTERNS

    g = GraphSession(spark, source="/root/testdata/sf0.001")
    for name in ("pat_standard", "pat_key_self", "pat_chain", "pat_poly_many", "pat_shared_row", "pat_virtual"):
        text = PATTERNS[name].text
        relation = duck("sf0.001").execute(to_sql(g.compiled(text)[1], Dialect.DUCKDB))
        names, rows = [d[0] for d in relation.description], relation.fetchall()
        assert parity(g.cypher(text), (names, rows))
        assert parity(g.sql(text), (names, rows))
