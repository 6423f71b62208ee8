"""Path forms, baselines, graph-level rewrites, vertex programs and catalog tools as queries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hopframe.baseline import algos, pointer, reencode
from hopframe.catalog import discover, validate
from hopframe.exec.session import GraphSession
from hopframe.graphopt import factor, triangles
from hopframe.measure.measures import plan_shape
from hopframe.paths import forms
from hopframe.workloads import patterns, snb
from hopframe.workloads.base import BOTH, HOT, HOT_BOTH, NB, TOUCH, Runner, Workload


def session(spark: SparkSession, sf_dir: str) -> GraphSession:
    return GraphSession(spark, source=sf_dir)


def touch(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    return events.select(F.col("user_id").alias("s0"), F.get_json_object("props", "$.k").cast("long").alias("t0"), F.col("event_id").alias("e0"), "event_type", "value", "ts")


def hot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return touch(spark, sf_dir).where("event_type = 'click' and value > 80")


def undirected(link: DataFrame) -> DataFrame:
    back = link.where("s0 <> t0").withColumns({"s0": F.col("t0"), "t0": F.col("s0")})
    return link.unionByName(back)


def seed(spark: SparkSession, *ids: int) -> DataFrame:
    return spark.createDataFrame([(i,) for i in ids], "s0 long")


def _reencoded(key: str, **how) -> Runner:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return reencode.reencode(session(spark, sf_dir), ["TOUCHED"], **how).session.cypher(snb.MICRO[key].text)

    return run


def _factorized(key: str) -> Runner:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        link = touch(spark, sf_dir)
        return {"tax_2hop_seed": lambda: factor.two_hop_count(link, seed(spark, 7)), "tax_3hop_seed": lambda: factor.three_hop_count(link, seed(spark, 7)), "tax_2hop_all": lambda: factor.two_hop_count(link)}[key]()

    return run


def _ranged(form: str) -> Runner:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return forms.ranged(hot(spark, sf_dir), 1, 4, form, seeds=seed(spark, 7)).groupBy(F.col("hops").alias("hops")).agg(F.count("*").alias("trails"), F.count_distinct("t0").alias("ends"))

    return run


def recursive_form(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The bounded range as the engine's own recursive common table expression; for small inputs only."""
    hot(spark, sf_dir).createOrReplaceTempView("hot_link")
    return spark.sql("""WITH RECURSIVE w(t0, hops, used) MAX RECURSION LEVEL 6 AS (SELECT t0, 1, array(e0) FROM hot_link WHERE s0 = 7
        UNION ALL SELECT h.t0, hops + 1, array_append(used, h.e0) FROM w JOIN hot_link h ON w.t0 = h.s0 WHERE hops < 4 AND NOT array_contains(used, h.e0))
        SELECT CAST(hops AS BIGINT) AS hops, count(*) AS trails, count(DISTINCT t0) AS ends FROM w GROUP BY hops""")


_RANGED = f"""WITH RECURSIVE {HOT}, w AS (SELECT dst, 1 AS hops, [id] AS used FROM hot WHERE src = 7 UNION ALL
    SELECT h.dst, hops + 1, list_append(used, h.id) FROM w JOIN hot h ON w.dst = h.src WHERE hops < 4 AND NOT list_contains(used, h.id)) SELECT hops, count(*) AS trails, count(DISTINCT dst) AS ends FROM w GROUP BY 1"""


def doubling_form(spark: SparkSession, sf_dir: str) -> DataFrame:
    part = spark.read.parquet(f"{sf_dir}/part.parquet")
    link = part.where("p_partkey > 0").select(F.col("p_partkey").alias("s0"), F.floor(F.col("p_partkey") / 10).alias("t0"))
    return forms.doubling(link, part.select(F.col("p_partkey").alias("s0"))).groupBy("hops").agg(F.count("*").alias("n"))


def frontier_distances(spark: SparkSession, sf_dir: str) -> DataFrame:
    return forms.frontier(hot(spark, sf_dir), seed(spark, 7), lo=0).groupBy("hops").agg(F.count("*").alias("n"))


def _all_shortest(link) -> Runner:
    """All shortest paths between accounts 7 and 50, with the sum of the values of their edges."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        edges = undirected(link(spark, sf_dir))
        pair = seed(spark, 7).withColumn("t0", F.lit(50).cast("long"))
        found = forms.shortest_paths(edges, seed(spark, 7), pairs=pair).select("hops", "nodes", F.col("used").alias("path"), F.explode("used").alias("edge"))
        valued = found.join(link(spark, sf_dir).select(F.col("e0").cast("string").alias("edge"), "value"), "edge")
        weighed = valued.groupBy("hops", "nodes", "path").agg(F.round(F.sum("value"), 6).alias("weight"))
        return weighed.select("hops", F.array_join(F.col("nodes").cast("array<string>"), "-").alias("nodes"), F.array_join("path", "-").alias("edges"), "weight")

    return run


def _shortest_sql(edges: str, table: str) -> str:
    """Distances from 7 over distinct neighbours, then paths traced back along falling distances."""
    return f"""WITH RECURSIVE {edges}, d0 AS (SELECT DISTINCT src, dst FROM {table}),
        w AS (SELECT CAST(7 AS BIGINT) AS t, 0 AS d UNION SELECT dst, d + 1 FROM w JOIN d0 ON t = src WHERE d < 12 AND t <> 50), m AS (SELECT t, min(d) AS d FROM w GROUP BY 1),
        p AS (SELECT t, d, d AS hops, CAST(t AS VARCHAR) AS nodes, '' AS edges, CAST(0 AS DOUBLE) AS weight FROM m WHERE t = 50
              UNION ALL SELECT e.src, p.d - 1, hops, e.src || '-' || nodes, e.id || CASE WHEN edges = '' THEN '' ELSE '-' || edges END, weight + e.v
              FROM p JOIN {table} e ON e.dst = p.t JOIN m ON m.t = e.src AND m.d = p.d - 1)
        SELECT CAST(hops AS BIGINT) AS hops, nodes, edges, round(weight, 6) AS weight FROM p WHERE d = 0 AND hops > 0"""


def _near_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of accounts, both ways, at the cost of one by the number of their interactions from the fifth day on."""
    window = touch(spark, sf_dir).where("ts >= timestamp_ntz'2024-01-05'")
    return undirected(window).groupBy("s0", "t0").agg((F.lit(1.0) / F.count("*")).alias("w"))


def _hot_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    return undirected(hot(spark, sf_dir)).withColumn("w", F.lit(100.0) / F.col("value"))


def _told(found: DataFrame) -> DataFrame:
    return found.select(F.col("t0").alias("id"), F.round("cost", 6).alias("cost"))


def _bi15(weights) -> Runner:
    """Cost of the cheapest path between accounts 7 and 50."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _told(forms.shortest(weights(spark, sf_dir), seed(spark, 7), spark.createDataFrame([(50,)], "t0 long"), "w"))

    return run


def _nation(spark: SparkSession, sf_dir: str, nation: int, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/customer.parquet").where(F.col("c_nationkey") == nation).select(F.col("c_custkey").alias(name))


def _bi19(weights) -> Runner:
    """For customers of nation 8 the cheapest path from any customer of nation 3, the cheapest twenty."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = forms.shortest(weights(spark, sf_dir), _nation(spark, sf_dir, 3, "s0"), _nation(spark, sf_dir, 8, "t0"), "w", together=True)
        return _told(found).orderBy("cost", "id").limit(20)

    return run


def _bi20(weights) -> Runner:
    """The cheapest paths from customer 7 to five customers served by supplier 5."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        served = session(spark, sf_dir).cypher("MATCH (s:Supplier {id: 5})-[:SHIPPED]->(o:Order)<-[:PLACED]-(c:Customer) WHERE c.id <> 7 RETURN DISTINCT c.id AS t0")
        return _told(forms.shortest(weights(spark, sf_dir), seed(spark, 7), served, "w")).orderBy("cost", "id").limit(5)

    return run


_NEAR_COSTS = f"{BOTH}, costs AS (SELECT src, dst, CAST(1 AS DOUBLE) / count(*) AS w FROM both_ways WHERE ts >= TIMESTAMP '2024-01-05' GROUP BY 1, 2)"
_HOT_COSTS = f"{HOT_BOTH}, costs AS (SELECT src, dst, min(100.0 / v) AS w FROM hu GROUP BY 1, 2)"
#: rounds of relaxation, twice as many as any of the given tables needs
_ROUNDS = 24


def _relaxed(costs: str, source: str, target: str, rest: str = "") -> str:
    """Distances from the sources taken together, relaxed round by round."""
    rounds = [f"c0 AS MATERIALIZED (SELECT s AS t, CAST(0 AS DOUBLE) AS cost FROM ({source}))"]
    rounds += [f"c{i} AS MATERIALIZED (SELECT t, min(cost) AS cost FROM (FROM c{i - 1} UNION ALL SELECT dst, cost + w FROM c{i - 1} JOIN costs ON t = src) GROUP BY 1)" for i in range(1, _ROUNDS + 1)]
    return f"WITH {costs}, {', '.join(rounds)} SELECT t AS id, round(cost, 6) AS cost FROM c{_ROUNDS} WHERE t IN ({target}) {rest}"


_SERVED = "SELECT o_custkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_suppkey = 5 AND o_custkey <> 7"
_CHEAPEST = {
    "bi15": (_bi15, ("SELECT 7 AS s", "SELECT 50")),
    "bi19": (_bi19, ("SELECT c_custkey AS s FROM customer WHERE c_nationkey = 3", "SELECT c_custkey FROM customer WHERE c_nationkey = 8", "ORDER BY cost, id LIMIT 20")),
    "bi20": (_bi20, ("SELECT 7 AS s", _SERVED, "ORDER BY cost, id LIMIT 5")),
}


def bi4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The customers with most orders from the top supplier of each nation."""
    g = session(spark, sf_dir)
    ranked = g.cypher("MATCH (n:Nation)<-[:BASED_IN]-(s:Supplier)-[:SHIPPED]->(o:Order) RETURN n.id AS nation, s.id AS supplier, count(DISTINCT o) AS k")
    top = ranked.groupBy("nation").agg(F.max(F.struct("k", (-F.col("supplier")).alias("s"))).alias("top")).select((-F.col("top.s")).alias("supplier"))
    served = g.cypher("MATCH (s:Supplier)-[:SHIPPED]->(o:Order)<-[:PLACED]-(c:Customer) RETURN s.id AS supplier, c.id AS customer, o.id AS order_id")
    found = served.join(top, "supplier", "left_semi").groupBy("customer").agg(F.count_distinct("order_id").alias("n"))
    return found.orderBy(F.desc("n"), "customer").limit(20)


def bi14(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each other nation the pair of a customer of nation 3 and one of its own that interact most, either way."""
    pairs = session(spark, sf_dir).cypher("MATCH (a:Customer {nation: 3})-[:INTERACTS]-(b:Customer) WHERE b.nation <> 3 RETURN b.nation AS nation, a.id AS a, b.id AS b, count(*) AS score")
    best = pairs.groupBy("nation").agg(F.max(F.struct("score", (-F.col("a")).alias("a"), (-F.col("b")).alias("b"))).alias("best"))
    return best.select("nation", (-F.col("best.a")).alias("a"), (-F.col("best.b")).alias("b"), "best.score")


def undirected_triangles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return triangles.undirected_triangles(touch(spark, sf_dir))


def directed_triangles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return triangles.directed_triangles(touch(spark, sf_dir))


def csr(spark: SparkSession, sf_dir: str) -> DataFrame:
    return forms.adjacency(touch(spark, sf_dir), chunk=16).groupBy("s0").agg(F.count("*").alias("parts"), F.sum(F.size("out")).cast("long").alias("edges"), F.max(F.size("out")).alias("widest")).select("s0", "edges")


def msbfs_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    return forms.multi_source(touch(spark, sf_dir), seed(spark, 7, 8, 9)).groupBy("s0", "hops").agg(F.count("*").alias("n"))


def msbfs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return forms.multi_source(hot(spark, sf_dir), seed(spark, 7, 8, 9)).groupBy("s0", "hops").agg(F.count("*").alias("n"))


def pagerank(spark: SparkSession, sf_dir: str) -> DataFrame:
    return algos.pagerank(hot(spark, sf_dir), rounds=3).select("node", F.round("rank", 6).alias("rank"))


def sssp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return algos.sssp(hot(spark, sf_dir), seed(spark, 7)).select("t0", F.col("cost").cast("long").alias("hops"))


def wcc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return algos.wcc(hot(spark, sf_dir))


def pagerank_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """PageRank over all events, with its default rounds."""
    return algos.pagerank(touch(spark, sf_dir)).select("node", F.round("rank", 6).alias("rank"))


def sssp_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    return algos.sssp(touch(spark, sf_dir), seed(spark, 7)).select("t0", F.col("cost").cast("long").alias("hops"))


def wcc_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    return algos.wcc(touch(spark, sf_dir))


#: the rounds of PageRank over all events, unrolled
_RANKS = ", ".join(
    f"r{i} AS MATERIALIZED (SELECT n.node, 0.15::DOUBLE / any_value(c) + 0.85 * coalesce(sum(r / deg), 0) AS r FROM n CROSS JOIN k LEFT JOIN f ON f.dst = n.node LEFT JOIN r{i - 1} p ON p.node = f.src GROUP BY 1)" for i in range(1, 11)
)


def pointer_walk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per-tuple traversal on the driver, over the slice of hot edges only."""
    lists = pointer.adjacency_lists(hot(spark, sf_dir), 2_000_000)
    counts = [(n, pointer.pointer_walk(lists, [7], n)) for n in (1, 2, 3, 4)]
    return spark.createDataFrame([x for x in counts if x[1]], "hops long, trails long")


def naive_shared_row(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = session(spark, sf_dir)
    g.gmap = reencode.uncoupled(g.gmap)
    return g.cypher("MATCH (o:Order)-[:CONTAINS]->(p:Part)-[:SOURCED_FROM]->(s:Supplier) RETURN count(*) AS n")


def reified(spark: SparkSession, sf_dir: str) -> DataFrame:
    return reencode.reified_lines(session(spark, sf_dir)).cypher("MATCH (o:Order)<-[:OF_ORDER]-(l:Line)-[:OF_SUPPLIER]->(s:Supplier), (l)-[:OF_PART]->(p:Part) RETURN s.name AS name, count(*) AS n")


def deep_validation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return validate.deep_checks(session(spark, sf_dir)).where("kind <> 'repeated rows of a keyless link'").groupBy("kind").agg(F.sum("rows").alias("rows"))


def discovered_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for t in ("customer", "orders", "part", "supplier", "nation"):
        own = discover.column_profile(t, spark.read.parquet(f"{sf_dir}/{t}.parquet"))
        out = own if out is None else out.unionByName(own)
    return out.where("kind <> 'string' and rows = values").select("table", "column")


def retrieved(spark: SparkSession, sf_dir: str) -> DataFrame:
    return session(spark, sf_dir).retrieve("TOUCHED", "Account", [7, 8], 2, 5).select("id", "hops")


def procedures(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = session(spark, sf_dir)
    return g.cypher("CALL db.labels() YIELD label AS name").withColumn("kind", F.lit("label")).unionByName(g.cypher("CALL db.relationshipTypes() YIELD relationshipType AS name").withColumn("kind", F.lit("type")))


def sql_text_mode(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same query by way of its generated SQL text."""
    return session(spark, sf_dir).sql(patterns.PATTERNS["pat_key_left"].text)


def graph_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pattern table function as a second front end."""
    return session(spark, sf_dir).graph_table("GRAPH_TABLE (commerce MATCH (c:Customer)-[:PLACED]->(o:Order) WHERE o.total > 400000 COLUMNS (c.name AS name, o.id AS order_id))")


def materialized(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = session(spark, sf_dir)
    g.materialize("asia_customers", g.cypher("MATCH (c:Customer)-[:LIVES_IN]->(n:Nation)-[:PART_OF]->(r:Region {name: 'ASIA'}) RETURN c.id AS id, n.name AS nation"))
    return spark.sql("SELECT nation, count(*) AS n FROM asia_customers GROUP BY nation")


def shapes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Joins in the plan of each strategy's query."""
    g = session(spark, sf_dir)
    queries = {"InRowScan": "MATCH (a:Account)-[:TOUCHED]->(b:Account) RETURN a.id AS a, b.id AS b", "EdgeChain": "MATCH (a:Account)-[:TOUCHED]->(b)-[:TOUCHED]->(c) RETURN a.id AS a, c.id AS c", "HalfInRow": "MATCH (c:Customer)-[:DID]->(t:Target) RETURN c.name AS c, t.id AS t", "KeyHop": "MATCH (c:Customer)-[:PLACED]->(o:Order) RETURN c.name AS c, o.total AS t", "TripleJoin": "MATCH (o:Order)-[:CONTAINS]->(p:Part) RETURN o.total AS t, p.name AS p", "SharedRow": "MATCH (o:Order)-[:CONTAINS]->(p:Part)-[:SOURCED_FROM]->(s:Supplier) RETURN o.id AS o, p.id AS p, s.id AS s"}
    return spark.createDataFrame([(k, plan_shape(g.cypher(q))["joins"]) for k, q in queries.items()], "strategy string, joins long")


_NATIVE = {k: snb.MICRO[k].oracle for k in snb.MICRO}
_LABELS = "Account Actor BenchItem Customer Document Host Lang Nation Order Page Part Quality Region Source Supplier Target Toxicity Turn Vector".split()
_TYPES = "ACTED BASED_IN CLICK COMPONENT_OF CONTAINS DID ERROR FLAGGED HOT_CLICK HOT_INTERACTS INTERACTS LED_BY LIVES_IN ON_HOST PART_OF PLACED PURCHASE RATED REPLY_OF SHIPPED SIGNUP SOURCED_FROM STARTED_BY TAGGED TOUCHED VIEW".split()
#: whole-number columns that discovery probes
_WHOLE = {"customer": ["c_custkey", "c_nationkey"], "orders": ["o_orderkey", "o_custkey"], "part": ["p_partkey", "p_size"], "supplier": ["s_suppkey", "s_nationkey"], "nation": ["n_nationkey", "n_regionkey"]}
_NAMES = ", ".join([f"('{n}', 'label')" for n in _LABELS] + [f"('{n}', 'type')" for n in _TYPES])

def _asked(text: str) -> Runner:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return session(spark, sf_dir).cypher(text)

    return run


def _trails(base: str, table: str, hi: int, where: str = "true") -> str:
    """Trails from account 7, edge by edge."""
    return f"""WITH RECURSIVE {base}, link AS (SELECT * FROM {table} WHERE {where}), w AS (SELECT CAST(7 AS BIGINT) AS t, 0 AS d, CAST([] AS BIGINT[]) AS used UNION ALL
        SELECT dst, d + 1, list_append(used, id) FROM w JOIN link ON t = src WHERE d < {hi} AND NOT list_contains(used, id))"""


#: what a match may do with a relationship does not hang on how its length is bounded
_SEMANTICS: dict[str, tuple[Runner, str | None]] = {
    "path_sem_second_hop": (_asked("MATCH (a:Account {id: 7})-[:HOT_CLICK*1..3]->(b)-[:HOT_CLICK]->(c) RETURN count(*) AS n"), _trails(HOT, "hot", 3) + " SELECT count(*) AS n FROM w JOIN hot ON t = src WHERE d > 0 AND NOT list_contains(used, id)"),
    "path_sem_second_hop_far": (_asked("MATCH (a:Account {id: 7})-[:HOT_CLICK*1..7]->(b)-[:HOT_CLICK]->(c) RETURN count(*) AS n"), _trails(HOT, "hot", 7) + " SELECT count(*) AS n FROM w JOIN hot ON t = src WHERE d > 0 AND NOT list_contains(used, id)"),
    "path_sem_edge_filter": (_asked("MATCH (a:Account {id: 7})-[:HOT_CLICK* {kind: 'view'}]->(b) RETURN b.id AS id"), _trails(HOT, "hot", 1, "ty = 'view'") + " SELECT t AS id FROM w WHERE d > 0"),
    "path_sem_edge_where": (_asked("MATCH (a:Account {id: 7})-[r:TOUCHED*1..7 WHERE r.value > 95]->(b) RETURN DISTINCT b.id AS id"), f"WITH RECURSIVE {TOUCH}, w AS (SELECT 7 AS t, 0 AS d UNION SELECT dst, d + 1 FROM w JOIN touch ON t = src WHERE v > 95 AND d < 7) SELECT DISTINCT t AS id FROM w WHERE d > 0"),
    "path_sem_undirected_filter": (_asked("MATCH (a:Account {id: 7})-[:HOT_CLICK*1..2 {kind: 'click'}]-(b) RETURN b.id AS id, count(*) AS n"), _trails(HOT_BOTH, "hu", 2) + " SELECT t AS id, count(*) AS n FROM w WHERE d > 0 GROUP BY 1"),
    "path_sem_longest": (_asked("MATCH p = (a:Account {id: 7})-[:HOT_CLICK*1..4]->(b) RETURN b.id AS id, max(length(p)) AS n"), _trails(HOT, "hot", 4) + " SELECT t AS id, max(d) AS n FROM w WHERE d > 0 GROUP BY 1"),
    "path_sem_lengths": (_asked("MATCH p = (a:Account {id: 7})-[:HOT_CLICK*1..7]->(b) RETURN DISTINCT b.id AS id, length(p) AS n"), _trails(HOT, "hot", 7) + " SELECT DISTINCT t AS id, d AS n FROM w WHERE d > 0"),
    "path_sem_undirected_ends": (_asked("MATCH p = (a:Account {id: 7})-[:HOT_CLICK*1..3]-(b) RETURN b.id AS id, min(length(p)) AS n"), _trails(HOT_BOTH, "hu", 3) + " SELECT t AS id, min(d) AS n FROM w WHERE d > 0 GROUP BY 1"),
    "path_sem_all_shortest": (_asked("MATCH p = allShortestPaths((a:Account {id: 7})-[:HOT_CLICK*]->(b:Account)) RETURN b.id AS id, length(p) AS n, count(*) AS paths"), f"WITH RECURSIVE {HOT}, d0 AS (SELECT DISTINCT src, dst FROM hot), w AS (SELECT CAST(7 AS BIGINT) AS t, 0 AS d UNION SELECT dst, d + 1 FROM w JOIN d0 ON t = src WHERE d < 14), m AS (SELECT t, min(d) AS d FROM w GROUP BY 1), p AS (SELECT t, d FROM m WHERE d = 0 UNION ALL SELECT m.t, m.d FROM p JOIN hot ON src = p.t JOIN m ON m.t = dst AND m.d = p.d + 1) SELECT t AS id, d AS n, count(*) AS paths FROM p WHERE d > 0 GROUP BY 1, 2"),
    "path_sem_renames": (_asked("MATCH (v0:Nation) WITH v0 AS v1 WITH v1 AS v2 WITH v2 AS v3 WITH v3 AS v4 WITH v4 AS v5 WITH v5 AS v6 RETURN v6.name AS name"), "SELECT n_name AS name FROM nation"),
}

EXTRA: dict[str, tuple[Runner, str | None]] = {
    **_SEMANTICS,
    **{f"{k}_reencoded": (_reencoded(k), _NATIVE[k]) for k in snb.MICRO},
    "tax_2hop_seed_map_blob": (_reencoded("tax_2hop_seed", blob="map"), _NATIVE["tax_2hop_seed"]),
    "tax_2hop_seed_typed": (_reencoded("tax_2hop_seed", layout="per_label"), _NATIVE["tax_2hop_seed"]),
    **{f"{k}_factorized": (_factorized(k), _NATIVE[k]) for k in snb.MICRO},
    **{f"path_form_{f}": (_ranged(f), _RANGED) for f in ("unrolled", "shared", "frontier")},
    "path_form_recursive": (recursive_form, _RANGED),
    "path_form_doubling": (doubling_form, snb.SOCIAL["path_forest"].oracle),
    "path_distances": (frontier_distances, f"WITH RECURSIVE {HOT}, w AS (SELECT 7 AS t, 0 AS d UNION SELECT dst, d + 1 FROM w JOIN hot ON t = src WHERE d < 12), m AS (SELECT t, min(d) AS hops FROM w GROUP BY 1) SELECT hops, count(*) AS n FROM m GROUP BY 1"),
    "ic14": (_all_shortest(touch), _shortest_sql(BOTH, "both_ways")),
    "ic14_sparse": (_all_shortest(hot), _shortest_sql(HOT_BOTH, "hu")),
    **{k: (make(_near_weights), _relaxed(_NEAR_COSTS, *sql)) for k, (make, sql) in _CHEAPEST.items()},
    **{f"{k}_sparse": (make(_hot_weights), _relaxed(_HOT_COSTS, *sql)) for k, (make, sql) in _CHEAPEST.items()},
    "bi4": (
        bi4,
        """WITH k AS (SELECT s_nationkey AS nation, l_suppkey AS supplier, count(DISTINCT l_orderkey) AS k FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2),
           top AS (SELECT supplier FROM k QUALIFY row_number() OVER (PARTITION BY nation ORDER BY k DESC, supplier) = 1)
           SELECT o_custkey AS customer, count(DISTINCT o_orderkey) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_suppkey IN (SELECT supplier FROM top) GROUP BY 1 ORDER BY n DESC, customer LIMIT 20""",
    ),
    "bi14": (
        bi14,
        f"""WITH {BOTH}, g AS (SELECT y.c_nationkey AS nation, src AS a, dst AS b, count(*) AS score FROM both_ways JOIN customer x ON x.c_custkey = src JOIN customer y ON y.c_custkey = dst WHERE x.c_nationkey = 3 AND y.c_nationkey <> 3 GROUP BY 1, 2, 3)
            SELECT nation, a, b, score FROM g QUALIFY row_number() OVER (PARTITION BY nation ORDER BY score DESC, a, b) = 1""",
    ),
    "tri_undirected": (undirected_triangles, f"WITH {TOUCH}, e AS (SELECT DISTINCT least(src, dst) AS x, greatest(src, dst) AS y FROM touch WHERE src <> dst) SELECT p.x AS a, p.y AS b, q.y AS c FROM e p JOIN e q ON p.y = q.x JOIN e r ON r.x = p.x AND r.y = q.y"),
    "tri_directed": (directed_triangles, f"WITH {TOUCH}, e AS (SELECT DISTINCT src, dst FROM touch WHERE src <> dst) SELECT p.src AS a, p.dst AS b, q.dst AS c FROM e p JOIN e q ON p.dst = q.src JOIN e r ON r.src = q.dst AND r.dst = p.src WHERE p.src < p.dst AND p.src < q.dst"),
    "csr_adjacency": (csr, f"WITH {TOUCH} SELECT src AS s0, count(*) AS edges FROM touch GROUP BY 1"),
    "msbfs_distances": (msbfs_all, f"WITH RECURSIVE {TOUCH}, e AS (SELECT DISTINCT src, dst FROM touch), w AS (SELECT s AS s0, s AS t, 0 AS d FROM (VALUES (7), (8), (9)) v(s) UNION SELECT s0, dst, d + 1 FROM w JOIN e ON t = src WHERE d < 8), m AS (SELECT s0, t, min(d) AS hops FROM w GROUP BY 1, 2) SELECT s0, hops, count(*) AS n FROM m GROUP BY 1, 2"),
    "msbfs_distances_sparse": (msbfs, f"WITH RECURSIVE {HOT}, w AS (SELECT s AS s0, s AS t, 0 AS d FROM (VALUES (7), (8), (9)) v(s) UNION SELECT s0, dst, d + 1 FROM w JOIN hot ON t = src WHERE d < 14), m AS (SELECT s0, t, min(d) AS hops FROM w GROUP BY 1, 2) SELECT s0, hops, count(*) AS n FROM m GROUP BY 1, 2"),
    "algo_pagerank_sparse": (
        pagerank,
        f"""WITH {HOT}, n AS (SELECT src AS node FROM hot UNION SELECT dst FROM hot), k AS (SELECT count(*) AS c FROM n), f AS (SELECT src, dst, count(*) OVER (PARTITION BY src) AS deg FROM hot),
            r0 AS (SELECT node, 1.0::DOUBLE / c AS r FROM n, k), r1 AS (SELECT n.node, 0.15::DOUBLE / (SELECT c FROM k) + 0.85 * coalesce((SELECT sum(r / deg) FROM f JOIN r0 ON r0.node = f.src WHERE f.dst = n.node), 0) AS r FROM n),
            r2 AS (SELECT n.node, 0.15::DOUBLE / (SELECT c FROM k) + 0.85 * coalesce((SELECT sum(r / deg) FROM f JOIN r1 ON r1.node = f.src WHERE f.dst = n.node), 0) AS r FROM n),
            r3 AS (SELECT n.node, 0.15::DOUBLE / (SELECT c FROM k) + 0.85 * coalesce((SELECT sum(r / deg) FROM f JOIN r2 ON r2.node = f.src WHERE f.dst = n.node), 0) AS r FROM n) SELECT node, round(r, 6) AS rank FROM r3""",
    ),
    "algo_sssp_sparse": (sssp, f"WITH RECURSIVE {HOT}, w AS (SELECT 7 AS t, 0 AS d UNION SELECT dst, d + 1 FROM w JOIN hot ON t = src WHERE d < 14) SELECT t AS t0, min(d) AS hops FROM w GROUP BY 1"),
    "algo_wcc_sparse": (wcc, f"WITH RECURSIVE {HOT_BOTH}, n AS (SELECT src AS node FROM hu UNION SELECT dst FROM hu), w AS (SELECT node, node AS r FROM n UNION SELECT w.node, dst FROM w JOIN hu ON r = src) SELECT node, min(r) AS component FROM w GROUP BY 1"),
    "algo_pagerank": (
        pagerank_all,
        f"""WITH {TOUCH}, n AS (SELECT src AS node FROM touch UNION SELECT dst FROM touch), k AS (SELECT count(*) AS c FROM n), f AS (SELECT src, dst, count(*) OVER (PARTITION BY src) AS deg FROM touch),
            r0 AS (SELECT node, 1.0::DOUBLE / c AS r FROM n, k), {_RANKS} SELECT node, round(r, 6) AS rank FROM r10""",
    ),
    "algo_sssp": (sssp_all, f"WITH RECURSIVE {TOUCH}, e AS (SELECT DISTINCT src, dst FROM touch), w AS (SELECT 7 AS t, 0 AS d UNION SELECT dst, d + 1 FROM w JOIN e ON t = src WHERE d < (SELECT count(DISTINCT dst) FROM touch)) SELECT t AS t0, min(d) AS hops FROM w GROUP BY 1"),
    "algo_wcc": (wcc_all, f"WITH RECURSIVE {BOTH}, e AS (SELECT DISTINCT src, dst FROM both_ways), n AS (SELECT src AS node FROM e UNION SELECT dst FROM e), w AS (SELECT node, node AS r FROM n UNION SELECT w.node, dst FROM w JOIN e ON r = src) SELECT node, min(r) AS component FROM w GROUP BY 1"),
    "base_pointer_walk": (pointer_walk, _RANGED.replace("count(*) AS trails, count(DISTINCT dst) AS ends", "count(*) AS trails")),
    "base_naive_shared_row": (naive_shared_row, "SELECT count(*) AS n FROM lineitem a JOIN lineitem b USING (l_partkey)"),
    "base_reified_lines": (reified, patterns.PATTERNS["pat_shared_row"].oracle),
    "tool_validate": (deep_validation, "SELECT * FROM (VALUES ('repeated key', 0), ('edge without its node', 0)) v(kind, rows)"),
    "tool_discover_keys": (discovered_keys, " UNION ALL ".join(f"SELECT '{t}' AS \"table\", '{x}' AS \"column\" FROM {t} HAVING count(*) = count(DISTINCT {x})" for t, xs in _WHOLE.items() for x in xs)),
    "tool_retrieve": (retrieved, f"WITH {TOUCH}, e AS (SELECT DISTINCT src, dst FROM touch), m AS (SELECT id, min(h) AS hops FROM (SELECT dst AS id, 1 AS h FROM e WHERE src IN (7, 8) UNION ALL SELECT y.dst, 2 FROM e x JOIN e y ON x.dst = y.src WHERE x.src IN (7, 8)) GROUP BY 1) SELECT id, hops FROM m QUALIFY row_number() OVER (PARTITION BY hops ORDER BY id) <= 5"),
    "tool_procedures": (procedures, f"SELECT * FROM (VALUES {_NAMES}) v(name, kind)"),
    "mode_sql_text": (sql_text_mode, patterns.PATTERNS["pat_key_left"].oracle),
    "pgq_graph_table": (graph_table, "SELECT c_name AS name, o_orderkey AS order_id FROM customer JOIN orders ON c_custkey = o_custkey WHERE o_totalprice > 400000"),
    "mode_materialize": (materialized, "SELECT n_name AS nation, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA' GROUP BY 1"),
    "measure_plan_shape": (shapes, "SELECT * FROM (VALUES ('InRowScan', 0), ('EdgeChain', 1), ('HalfInRow', 1), ('KeyHop', 1), ('TripleJoin', 2), ('SharedRow', 0)) v(strategy, joins)"),
}

#: counts that the compiler takes without expanding, and path procedures
COMPILED = {
    "count_chain_3hop": Workload(
        "MATCH (a:Account)-[:TOUCHED]->(b)-[:TOUCHED]->(c)-[:TOUCHED]->(d) RETURN count(*) AS n",
        f"WITH {TOUCH} SELECT count(*) AS n FROM touch x JOIN touch y ON x.dst = y.src JOIN touch z ON y.dst = z.src WHERE x.id <> y.id AND y.id <> z.id AND x.id <> z.id",
    ),
    "count_star_orders_clicks": Workload(
        "MATCH (c:Customer)-[:PLACED]->(o:Order)-[:CONTAINS]->(p:Part), (c)-[:INTERACTS]->(d) RETURN count(*) AS n",
        f"""WITH {TOUCH} SELECT count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN part ON l_partkey = p_partkey
            JOIN customer a ON o_custkey = a.c_custkey JOIN touch ON src = a.c_custkey JOIN customer b ON dst = b.c_custkey""",
    ),
    "proc_reachable": Workload(
        "CALL path.reachable('Account', 7, 'HOT_CLICK', 4) YIELD id, hops RETURN id, hops",
        f"""WITH RECURSIVE {HOT}, w AS (SELECT dst AS id, 1 AS d FROM hot WHERE src = 7 UNION SELECT dst, d + 1 FROM w JOIN hot ON w.id = src WHERE d < 4)
            SELECT id, min(d) AS hops FROM w GROUP BY 1""",
    ),
    "proc_distance": Workload(
        "CALL path.distance('Customer', 7, 8, 'INTERACTS', 5) YIELD hops AS far RETURN far",
        f"""WITH RECURSIVE {TOUCH}, e AS (SELECT DISTINCT src, dst FROM touch), w AS (SELECT dst AS id, 1 AS d FROM e WHERE src = 7 UNION SELECT dst, d + 1 FROM w JOIN e ON id = src WHERE d < 5)
            SELECT min(d) AS far FROM w WHERE id = 8 HAVING count(*) > 0""",
    ),
}
EXTRA |= {k: (w, w.oracle) for k, w in COMPILED.items()}
