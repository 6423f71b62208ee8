"""One query for each mapping pattern and join strategy, and for compositions of them."""

from __future__ import annotations

from hopframe.workloads.base import TOUCH, Workload

PATTERNS: dict[str, Workload] = {
    "pat_standard": Workload(
        "MATCH (o:Order)-[r:CONTAINS]->(p:Part) WHERE p.type STARTS WITH 'PROMO' RETURN o.status AS status, count(*) AS n, sum(r.quantity) AS quantity",
        "SELECT o_orderstatus AS status, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey WHERE p_type LIKE 'PROMO%' GROUP BY 1",
    ),
    "pat_key_left": Workload(
        "MATCH (c:Customer)-[:LIVES_IN]->(n:Nation)-[:PART_OF]->(r:Region) RETURN r.name AS region, count(*) AS n",
        "SELECT r_name AS region, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1",
    ),
    "pat_key_right": Workload(
        "MATCH (c:Customer {segment: 'BUILDING'})-[:PLACED]->(o:Order) RETURN c.name AS name, count(*) AS n, sum(o.total) AS total",
        "SELECT c_name AS name, count(*) AS n, sum(o_totalprice) AS total FROM customer JOIN orders ON c_custkey = o_custkey WHERE c_mktsegment = 'BUILDING' GROUP BY 1",
    ),
    "pat_key_self": Workload(
        "MATCH (a:Part)-[:COMPONENT_OF]->(b:Part) RETURN b.id AS parent, count(*) AS n, min(a.name) AS least",
        "SELECT b.p_partkey AS parent, count(*) AS n, min(a.p_name) AS least FROM part a JOIN part b ON a.p_partkey > 0 AND b.p_partkey = a.p_partkey // 10 GROUP BY 1",
    ),
    "pat_key_self_composite": Workload(
        "MATCH (a:Turn)-[:REPLY_OF]->(b:Turn) RETURN a.role AS role, b.role AS of, count(*) AS n",
        "SELECT a.role AS role, b.role AS of, count(*) AS n FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn - 1 GROUP BY 1, 2",
    ),
    "pat_key_cyclic": Workload(
        "MATCH (a:Nation)-[:LED_BY*1..4]->(b:Nation) RETURN a.id AS a, b.id AS b, count(*) AS trails",
        """WITH RECURSIVE l AS (SELECT n_nationkey AS s, n_regionkey AS t FROM nation),
           w AS (SELECT s AS a, t AS b, [s] AS used FROM l UNION ALL SELECT w.a, l.t, list_append(used, l.s) FROM w JOIN l ON w.b = l.s WHERE NOT list_contains(used, l.s) AND len(used) < 4)
           SELECT a, b, count(*) AS trails FROM w GROUP BY 1, 2""",
    ),
    "pat_denorm": Workload(
        "MATCH (a:Account)-[r:TOUCHED]->(b:Account) WHERE r.value > 100 RETURN b.id AS id, count(*) AS n, max(r.value) AS most",
        f"WITH {TOUCH} SELECT dst AS id, count(*) AS n, max(v) AS most FROM touch WHERE v > 100 GROUP BY 1",
    ),
    "pat_half": Workload(
        "MATCH (c:Customer)-[r:DID]->(t:Target) WHERE r.kind = 'purchase' RETURN c.segment AS segment, count(*) AS n, count(DISTINCT t) AS targets",
        f"WITH {TOUCH} SELECT c_mktsegment AS segment, count(*) AS n, count(DISTINCT dst) AS targets FROM touch JOIN customer ON src = c_custkey WHERE ty = 'purchase' GROUP BY 1",
    ),
    "pat_chain": Workload(
        "MATCH (a:Account)-[x:TOUCHED]->(b)-[y:TOUCHED]->(c) WHERE x.value > 100 AND y.value > 100 RETURN a.id AS a, count(*) AS n, count(DISTINCT c) AS ends",
        f"WITH {TOUCH} SELECT x.src AS a, count(*) AS n, count(DISTINCT y.dst) AS ends FROM touch x JOIN touch y ON x.dst = y.src AND x.id <> y.id WHERE x.v > 100 AND y.v > 100 GROUP BY 1",
    ),
    "pat_poly_one": Workload(
        "MATCH (a:Customer)-[:PURCHASE]->(b:Customer) RETURN b.segment AS segment, count(*) AS n",
        f"WITH {TOUCH} SELECT c_mktsegment AS segment, count(*) AS n FROM touch JOIN customer ON dst = c_custkey WHERE ty = 'purchase' GROUP BY 1",
    ),
    "pat_poly_many": Workload(
        "MATCH (a:Customer)-[r:CLICK|VIEW]->(b:Customer) RETURN type(r) AS kind, a.segment AS segment, count(*) AS n",
        f"WITH {TOUCH} SELECT upper(ty) AS kind, c_mktsegment AS segment, count(*) AS n FROM touch JOIN customer ON src = c_custkey WHERE ty IN ('click', 'view') GROUP BY 1, 2",
    ),
    "pat_poly_any": Workload(
        "MATCH (a:Document)-[r]->(b) RETURN type(r) AS kind, labels(b)[0] AS label, count(*) AS n",
        """SELECT 'TAGGED' AS kind, 'Lang' AS label, count(lang) AS n FROM documents UNION ALL SELECT 'TAGGED', 'Source', count(source) FROM documents
           UNION ALL SELECT 'RATED', 'Quality', count(*) FROM labels UNION ALL SELECT 'FLAGGED', 'Toxicity', count(*) FROM labels""",
    ),
    "pat_poly_endpoint": Workload(
        "MATCH (d:Document)-[:TAGGED]->(x) RETURN labels(x)[0] AS label, x.name AS name, count(*) AS n",
        "SELECT 'Lang' AS label, lang AS name, count(*) AS n FROM documents GROUP BY 2 UNION ALL SELECT 'Source', source, count(*) FROM documents GROUP BY 2",
    ),
    "pat_composite": Workload(
        "MATCH (t:Turn {conv: 3, turn: 1})-[:STARTED_BY]->(c:Customer) RETURN t.conv AS conv, t.turn AS turn, t.role AS role, c.name AS name",
        "SELECT conv_id AS conv, turn, role, c_name AS name FROM conversations JOIN customer ON conv_id = c_custkey WHERE conv_id = 3 AND turn = 1",
    ),
    "pat_shared_row": Workload(
        "MATCH (o:Order)-[:CONTAINS]->(p:Part)-[:SOURCED_FROM]->(s:Supplier) RETURN s.name AS name, count(*) AS n",
        "SELECT s_name AS name, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1",
    ),
    "pat_shared_row_labels": Workload(
        "MATCH (t:Toxicity)<-[:FLAGGED]-(d:Document)-[:RATED]->(q:Quality) RETURN q.value AS quality, t.value AS toxic, count(*) AS n",
        "SELECT quality, toxic, count(*) AS n FROM labels GROUP BY 1, 2",
    ),
    "pat_virtual": Workload(
        "MATCH (p:Page)-[:ON_HOST]->(h:Host) RETURN h.name AS host, count(*) AS n",
        "SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1",
    ),
    "pat_compose_all": Workload(
        "MATCH (a:Actor)-[:ACTED]->(b:Account) RETURN a.id AS id, a.kind AS kind, count(*) AS n, count(DISTINCT b) AS targets",
        f"WITH {TOUCH} SELECT src AS id, ty AS kind, count(*) AS n, count(DISTINCT dst) AS targets FROM touch WHERE ty IN ('click', 'view') GROUP BY 1, 2",
    ),
    "pat_inlined_label": Workload(
        "MATCH (a:Account) RETURN count(*) AS n",
        f"WITH {TOUCH} SELECT count(*) AS n FROM (SELECT src FROM touch UNION SELECT dst FROM touch)",
    ),
    "pat_undirected": Workload(
        "MATCH (a:Account {id: 7})-[r:TOUCHED]-(b:Account) RETURN b.id AS id, count(*) AS n",
        f"WITH {TOUCH} SELECT id, count(*) AS n FROM (SELECT dst AS id FROM touch WHERE src = 7 UNION ALL SELECT src FROM touch WHERE dst = 7 AND src <> 7) GROUP BY 1",
    ),
}
