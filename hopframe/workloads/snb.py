"""The 41 social-network benchmark queries restated on the commerce graph, and the micro, flights and social ones."""

from __future__ import annotations

from hopframe.workloads.base import BOTH, HOT, HOT_BOTH, NB, NEAR2, TOUCH, Workload

MICRO: dict[str, Workload] = {
    "tax_2hop_seed": Workload("MATCH (a:Account {id: 7})-[:TOUCHED]->(b)-[:TOUCHED]->(c) RETURN count(*) AS n", f"WITH {TOUCH} SELECT count(*) AS n FROM touch x JOIN touch y ON x.dst = y.src AND x.id <> y.id WHERE x.src = 7"),
    "tax_3hop_seed": Workload("MATCH (a:Account {id: 7})-[:TOUCHED*3]->(c) RETURN count(*) AS n", f"WITH {TOUCH} SELECT count(*) AS n FROM touch x JOIN touch y ON x.dst = y.src AND x.id <> y.id JOIN touch z ON y.dst = z.src AND z.id <> y.id AND z.id <> x.id WHERE x.src = 7"),
    "tax_2hop_all": Workload("MATCH (a:Account)-[:TOUCHED]->(b)-[:TOUCHED]->(c) RETURN count(*) AS n", f"WITH {TOUCH} SELECT count(*) AS n FROM touch x JOIN touch y ON x.dst = y.src AND x.id <> y.id"),
}

FLIGHTS: dict[str, Workload] = {
    "ot_q1_two_hop": Workload(
        "MATCH (a:Account {id: 7})-[x:TOUCHED]->(b)-[y:TOUCHED]->(c) WHERE date(x.ts) = date('2024-01-05') AND y.ts > x.ts RETURN c.id AS id, count(*) AS n",
        f"WITH {TOUCH} SELECT y.dst AS id, count(*) AS n FROM touch x JOIN touch y ON x.dst = y.src AND x.id <> y.id WHERE x.src = 7 AND CAST(x.ts AS DATE) = DATE '2024-01-05' AND y.ts > x.ts GROUP BY 1",
    ),
    "ot_q2_delayed_two_hop": Workload(
        "MATCH (a:Account {id: 7})-[x:TOUCHED]->(b)-[y:TOUCHED]->(c) WHERE x.value > 100 AND y.value > 100 RETURN c.id AS id, count(*) AS n",
        f"WITH {TOUCH} SELECT y.dst AS id, count(*) AS n FROM touch x JOIN touch y ON x.dst = y.src AND x.id <> y.id WHERE x.src = 7 AND x.v > 100 AND y.v > 100 GROUP BY 1",
    ),
    "ot_q3_hub": Workload(
        "MATCH (a:Account)-[:TOUCHED]-(b:Account) RETURN a.id AS id, count(*) AS traffic ORDER BY traffic DESC, id LIMIT 10",
        f"WITH {BOTH} SELECT src AS id, count(*) AS traffic FROM both_ways GROUP BY 1 ORDER BY traffic DESC, id LIMIT 10",
    ),
    "ot_q4_three_hop": Workload(
        "MATCH (a:Account {id: 7})-[x:TOUCHED]->(b)-[y:TOUCHED]->(c)-[z:TOUCHED]->(d) WHERE y.ts > x.ts AND z.ts > y.ts RETURN count(DISTINCT d) AS n, count(*) AS routes",
        f"WITH {TOUCH} SELECT count(DISTINCT z.dst) AS n, count(*) AS routes FROM touch x JOIN touch y ON x.dst = y.src AND y.ts > x.ts JOIN touch z ON y.dst = z.src AND z.ts > y.ts WHERE x.src = 7",
    ),
}

_WALK = f"""WITH RECURSIVE {HOT}, w AS (SELECT dst, 1 AS d, [id] AS used FROM hot WHERE src = {{seed}} UNION ALL
    SELECT h.dst, d + 1, list_append(used, h.id) FROM w JOIN hot h ON w.dst = h.src WHERE d < {{hi}} AND NOT list_contains(used, h.id))"""

SOCIAL: dict[str, Workload] = {
    "social_exact3": Workload(
        "MATCH (a:Customer {name: 'Customer#000000007'})-[:HOT_INTERACTS*3]->(c:Customer) RETURN DISTINCT c.name AS name",
        _WALK.format(seed=7, hi=3) + " SELECT DISTINCT c_name AS name FROM w JOIN customer ON dst = c_custkey WHERE d = 3",
    ),
    "social_range13": Workload(
        "MATCH (a:Customer {name: 'Customer#000000007'})-[:HOT_INTERACTS*1..3]->(c:Customer) RETURN DISTINCT c.name AS name",
        _WALK.format(seed=7, hi=3) + " SELECT DISTINCT c_name AS name FROM w JOIN customer ON dst = c_custkey",
    ),
    **{
        f"social_expand_{n}": Workload(
            f"MATCH p = (a:Account {{id: 7}})-[:HOT_CLICK*1..{n}]->(b:Account) RETURN b.id AS id, min(length(p)) AS hops",
            _WALK.format(seed=7, hi=n) + " SELECT dst AS id, min(d) AS hops FROM w GROUP BY 1",
        )
        for n in (1, 2, 3)
    },
    "path_open_reach": Workload(
        "MATCH (a:Account {id: 7})-[:HOT_CLICK*1..]->(b:Account) RETURN DISTINCT b.id AS id",
        f"WITH RECURSIVE {HOT}, w AS (SELECT dst FROM hot WHERE src = 7 UNION SELECT h.dst FROM w JOIN hot h ON w.dst = h.src) SELECT dst AS id FROM w",
    ),
    "path_zero_length": Workload(
        "MATCH p = (a:Account {id: 7})-[:HOT_CLICK*0..2]->(b:Account) RETURN b.id AS id, min(length(p)) AS hops",
        _WALK.format(seed=7, hi=2) + " SELECT id, min(h) AS hops FROM (SELECT dst AS id, d AS h FROM w UNION ALL SELECT 7, 0) GROUP BY 1",
    ),
    "path_forest": Workload(
        "MATCH p = (a:Part)-[:COMPONENT_OF*0..]->(b:Part) RETURN length(p) AS hops, count(*) AS n",
        "WITH RECURSIVE w AS (SELECT p_partkey AS s, p_partkey AS t, 0 AS hops FROM part UNION ALL SELECT s, t // 10, hops + 1 FROM w WHERE t > 0) SELECT hops, count(*) AS n FROM w GROUP BY 1",
    ),
    "path_replies": Workload(
        "MATCH p = (a:Turn)-[:REPLY_OF*0..]->(b:Turn) RETURN length(p) AS hops, count(*) AS n",
        "SELECT a.turn - b.turn AS hops, count(*) AS n FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn <= a.turn GROUP BY 1",
    ),
}

_T = "localdatetime('{0}')"
_CONV = "r AS (SELECT a.conv_id, a.turn AS from_turn, a.role AS from_role, b.turn AS to_turn FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn <= a.turn)"

SHORT: dict[str, Workload] = {
    "is1": Workload("MATCH (c:Customer {id: 7})-[:LIVES_IN]->(n:Nation) RETURN c.name AS customer, c.segment AS segment, n.name AS nation", "SELECT c_name AS customer, c_mktsegment AS segment, n_name AS nation FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE c_custkey = 7"),
    "is2": Workload(
        "MATCH (t:Turn {conv: 3})-[:REPLY_OF*0..]->(root:Turn {turn: 0}) WITH t, root MATCH (root)-[:STARTED_BY]->(c:Customer) RETURN t.turn AS turn, t.role AS role, root.role AS root_role, c.name AS starter ORDER BY turn DESC LIMIT 10",
        "SELECT t.turn, t.role, r.role AS root_role, c_name AS starter FROM conversations t JOIN conversations r ON r.conv_id = t.conv_id AND r.turn = 0 JOIN customer ON c_custkey = r.conv_id WHERE t.conv_id = 3 ORDER BY t.turn DESC LIMIT 10",
    ),
    "is3": Workload("MATCH (c:Customer {id: 7})-[r:INTERACTS]-(d:Customer) RETURN d.id AS friend, d.name AS name, max(r.ts) AS latest", f"WITH {BOTH} SELECT dst AS friend, c_name AS name, max(ts) AS latest FROM both_ways JOIN customer ON dst = c_custkey WHERE src = 7 GROUP BY 1, 2"),
    "is4": Workload("MATCH (t:Turn {conv: 3, turn: 1}) RETURN t.text AS text, t.role AS role", "SELECT text, role FROM conversations WHERE conv_id = 3 AND turn = 1"),
    "is5": Workload("MATCH (t:Turn {conv: 3, turn: 1})-[:STARTED_BY]->(c:Customer) RETURN c.id AS id, c.name AS name", "SELECT c_custkey AS id, c_name AS name FROM customer WHERE c_custkey = 3"),
    "is6": Workload(
        "MATCH (t:Turn {conv: 3, turn: 1})-[:REPLY_OF*0..]->(r:Turn {turn: 0})-[:STARTED_BY]->(c:Customer)-[:LIVES_IN]->(n:Nation) RETURN r.conv AS conv, c.name AS name, n.name AS nation",
        "SELECT CAST(3 AS BIGINT) AS conv, c_name AS name, n_name AS nation FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE c_custkey = 3",
    ),
    "is7": Workload(
        "MATCH (t:Turn {conv: 7, turn: 0})<-[:REPLY_OF]-(r:Turn) MATCH (t)-[:STARTED_BY]->(a:Customer), (r)-[:STARTED_BY]->(b:Customer) OPTIONAL MATCH (a)-[k:INTERACTS]-(b) RETURN r.turn AS turn, r.role AS role, b.name AS author, count(k) > 0 AS interacts",
        f"WITH {TOUCH} SELECT turn, role, c_name AS author, (SELECT count(*) FROM touch WHERE src = 7 AND dst = 7) > 0 AS interacts FROM conversations JOIN customer ON conv_id = c_custkey WHERE conv_id = 7 AND turn = 1",
    ),
}

COMPLEX: dict[str, Workload] = {
    "ic1": Workload(
        """MATCH p = (c:Customer {id: 7})-[:INTERACTS*1..3]-(d:Customer {segment: 'BUILDING'}) WHERE d.id <> 7
           WITH d, min(length(p)) AS dist ORDER BY dist, d.id LIMIT 20
           MATCH (d)-[:LIVES_IN]->(n:Nation) OPTIONAL MATCH (d)-[:PLACED]->(o:Order)
           RETURN d.id AS id, d.name AS name, dist, n.name AS nation, sort(collect(o.id)) AS orders""",
        f"""WITH RECURSIVE {NB}, w AS (SELECT 7 AS t, 0 AS d UNION SELECT dst, d + 1 FROM w JOIN nb ON t = src WHERE d < 3),
            m AS (SELECT t, min(d) AS dist FROM w JOIN customer ON t = c_custkey WHERE t <> 7 AND c_mktsegment = 'BUILDING' GROUP BY 1 ORDER BY dist, t LIMIT 20)
            SELECT c_custkey AS id, c_name AS name, CAST(dist AS BIGINT) AS dist, n_name AS nation,
                   coalesce((SELECT list_sort(list(o_orderkey)) FROM orders WHERE o_custkey = c_custkey), []) AS orders
            FROM m JOIN customer ON t = c_custkey JOIN nation ON c_nationkey = n_nationkey""",
    ),
    "ic2": Workload(
        "MATCH (c:Customer {id: 7})-[:INTERACTS]-(d:Customer) WITH DISTINCT d MATCH (d)-[:PLACED]->(o:Order) WHERE o.date < localdatetime('1998-01-01') RETURN d.id AS friend, o.id AS order_id, o.date AS date ORDER BY date DESC, order_id LIMIT 20",
        f"WITH {BOTH} SELECT o_custkey AS friend, o_orderkey AS order_id, o_orderdate AS date FROM orders WHERE o_custkey IN (SELECT dst FROM both_ways WHERE src = 7) AND o_orderdate < TIMESTAMP '1998-01-01' ORDER BY date DESC, order_id LIMIT 20",
    ),
    "ic3": Workload(
        "MATCH (c:Customer {id: 7})-[:INTERACTS*1..2]-(d:Customer) WHERE d.id <> 7 WITH DISTINCT d MATCH (d)-[:PLACED]->(o:Order)-[:CONTAINS]->(p:Part)-[:SOURCED_FROM]->(s:Supplier)-[:BASED_IN]->(n:Nation) WHERE n.id IN [3, 8] AND o.date >= localdatetime('1998-01-01') WITH d, sum(CASE WHEN n.id = 3 THEN 1 ELSE 0 END) AS x, sum(CASE WHEN n.id = 8 THEN 1 ELSE 0 END) AS y WHERE x > 0 AND y > 0 RETURN d.id AS id, x, y",
        f"""WITH {NEAR2}, g AS (SELECT o_custkey AS id, CAST(sum(CASE WHEN s_nationkey = 3 THEN 1 ELSE 0 END) AS BIGINT) AS x, CAST(sum(CASE WHEN s_nationkey = 8 THEN 1 ELSE 0 END) AS BIGINT) AS y
            FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN supplier ON l_suppkey = s_suppkey WHERE o_custkey IN (SELECT id FROM near2) AND o_orderdate >= TIMESTAMP '1998-01-01' GROUP BY 1) SELECT * FROM g WHERE x > 0 AND y > 0""",
    ),
    "ic4": Workload(
        "MATCH (c:Customer {id: 7})-[:INTERACTS]-(d:Customer) WITH DISTINCT d MATCH (d)-[:PLACED]->(o:Order)-[:CONTAINS]->(p:Part) WHERE o.date < localdatetime('1998-07-01') WITH p, min(o.date) AS first, count(*) AS n WHERE first >= localdatetime('1998-01-01') RETURN p.id AS part, n ORDER BY n DESC, part LIMIT 10",
        f"""WITH {BOTH}, g AS (SELECT l_partkey AS part, min(o_orderdate) AS first, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_custkey IN (SELECT dst FROM both_ways WHERE src = 7) AND o_orderdate < TIMESTAMP '1998-07-01' GROUP BY 1)
            SELECT part, n FROM g WHERE first >= TIMESTAMP '1998-01-01' ORDER BY n DESC, part LIMIT 10""",
    ),
    "ic5": Workload(
        "MATCH (c:Customer {id: 7})-[:INTERACTS*1..2]-(d:Customer) WHERE d.id <> 7 WITH collect(DISTINCT d) AS ds UNWIND ds AS d MATCH (d)-[:PLACED]->(o:Order)<-[:SHIPPED]-(s:Supplier) WHERE o.date > localdatetime('2000-01-01') RETURN s.id AS supplier, count(DISTINCT o) AS orders ORDER BY orders DESC, supplier LIMIT 20",
        f"WITH {NEAR2} SELECT l_suppkey AS supplier, count(DISTINCT o_orderkey) AS orders FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_custkey IN (SELECT id FROM near2) AND o_orderdate > TIMESTAMP '2000-01-01' GROUP BY 1 ORDER BY orders DESC, supplier LIMIT 20",
    ),
    "ic6": Workload(
        "MATCH (c:Customer {id: 7})-[:INTERACTS]-(d:Customer) WITH DISTINCT d MATCH (d)-[:PLACED]->(o:Order)-[:CONTAINS]->(p:Part {id: 42}) WITH DISTINCT o MATCH (o)-[:CONTAINS]->(q:Part) WHERE q.id <> 42 RETURN q.id AS part, count(DISTINCT o) AS n ORDER BY n DESC, part LIMIT 10",
        f"""WITH {BOTH}, h AS (SELECT DISTINCT o_orderkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_partkey = 42 AND o_custkey IN (SELECT dst FROM both_ways WHERE src = 7))
            SELECT l_partkey AS part, count(DISTINCT l_orderkey) AS n FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM h) AND l_partkey <> 42 GROUP BY 1 ORDER BY n DESC, part LIMIT 10""",
    ),
    "ic7": Workload(
        "MATCH (c:Customer {id: 7})<-[r:INTERACTS]-(d:Customer) WITH d, max(r.ts) AS latest RETURN d.id AS sender, d.name AS name, latest, EXISTS { (d)<-[:INTERACTS]-(x:Customer {id: 7}) } AS mutual ORDER BY latest DESC, sender LIMIT 20",
        f"WITH {TOUCH}, g AS (SELECT src, max(ts) AS latest FROM touch WHERE dst = 7 GROUP BY 1) SELECT src AS sender, c_name AS name, latest, src IN (SELECT dst FROM touch WHERE src = 7) AS mutual FROM g JOIN customer ON src = c_custkey ORDER BY latest DESC, sender LIMIT 20",
    ),
    "ic8": Workload(
        "MATCH (c:Customer {id: 3})<-[:STARTED_BY]-(t:Turn)<-[:REPLY_OF]-(r:Turn) RETURN r.conv AS conv, r.turn AS turn, r.role AS role ORDER BY turn DESC LIMIT 20",
        "SELECT conv_id AS conv, turn, role FROM conversations WHERE conv_id = 3 AND turn > 0 ORDER BY turn DESC LIMIT 20",
    ),
    "ic9": Workload(
        "MATCH (c:Customer {id: 7})-[:INTERACTS*1..2]-(d:Customer) WHERE d.id <> 7 WITH collect(DISTINCT d) AS ds UNWIND ds AS d MATCH (d)-[:PLACED]->(o:Order) WHERE o.date < localdatetime('1998-01-01') RETURN d.id AS friend, d.name AS name, o.id AS order_id ORDER BY o.date DESC, order_id LIMIT 20",
        f"WITH {NEAR2} SELECT o_custkey AS friend, c_name AS name, o_orderkey AS order_id FROM orders JOIN customer ON o_custkey = c_custkey WHERE o_custkey IN (SELECT id FROM near2) AND o_orderdate < TIMESTAMP '1998-01-01' ORDER BY o_orderdate DESC, order_id LIMIT 20",
    ),
    "ic10": Workload(
        """MATCH (c:Customer {id: 7})-[:INTERACTS*2]-(d:Customer) WHERE d.id <> 7 AND NOT (c)-[:INTERACTS]-(d) WITH DISTINCT c, d
           MATCH (c)-[:PLACED]->(:Order)-[:CONTAINS]->(p:Part) WITH d, collect(DISTINCT p.type) AS types
           MATCH (d)-[:PLACED]->(:Order)-[:CONTAINS]->(q:Part) WHERE q.type IN types
           RETURN d.id AS id, count(DISTINCT q.type) AS score ORDER BY score DESC, id LIMIT 10""",
        f"""WITH {NB}, two AS (SELECT DISTINCT y.dst AS id FROM nb x JOIN nb y ON x.dst = y.src WHERE x.src = 7 AND y.dst <> 7 AND y.dst NOT IN (SELECT dst FROM nb WHERE src = 7)),
            bought AS (SELECT DISTINCT o_custkey AS id, p_type FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN part ON l_partkey = p_partkey)
            SELECT b.id, count(*) AS score FROM bought b JOIN two USING (id) WHERE p_type IN (SELECT p_type FROM bought WHERE id = 7) GROUP BY 1 ORDER BY score DESC, b.id LIMIT 10""",
    ),
    "ic11": Workload(
        "MATCH (c:Customer {id: 7})-[:INTERACTS*1..2]-(d:Customer) WHERE d.id <> 7 WITH DISTINCT d MATCH (d)-[:PLACED]->(o:Order)-[:CONTAINS]->(p:Part)-[r:SOURCED_FROM]->(s:Supplier)-[:BASED_IN]->(n:Nation {id: 3}) WHERE r.shipped < localdatetime('1998-01-01') RETURN d.id AS id, s.name AS supplier, count(*) AS n",
        f"WITH {NEAR2} SELECT o_custkey AS id, s_name AS supplier, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN supplier ON l_suppkey = s_suppkey WHERE s_nationkey = 3 AND l_shipdate < TIMESTAMP '1998-01-01' AND o_custkey IN (SELECT id FROM near2) GROUP BY 1, 2",
    ),
    "ic12": Workload(
        """MATCH (q:Part)-[:COMPONENT_OF*0..]->(a:Part {id: 4}) WITH DISTINCT q
           MATCH (q)<-[:CONTAINS]-(o:Order)<-[:PLACED]-(d:Customer)-[:INTERACTS]-(c:Customer {id: 7})
           RETURN d.id AS id, count(DISTINCT o) AS orders, sort(collect(DISTINCT q.name)) AS names""",
        f"""WITH {NB}, under AS (SELECT p_partkey, p_name FROM part WHERE p_partkey > 0 AND starts_with(CAST(p_partkey AS VARCHAR), '4'))
            SELECT o_custkey AS id, count(DISTINCT o_orderkey) AS orders, list_sort(list(DISTINCT p_name)) AS names
            FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN under ON l_partkey = p_partkey WHERE o_custkey IN (SELECT dst FROM nb WHERE src = 7) GROUP BY 1""",
    ),
    "ic13": Workload(
        "MATCH (a:Customer {id: 7}), (b:Customer {id: 50}) OPTIONAL MATCH p = shortestPath((a)-[:INTERACTS*..15]-(b)) RETURN coalesce(length(p), -1) AS hops",
        f"WITH RECURSIVE {NB}, w AS (SELECT 7 AS t, 0 AS d UNION SELECT dst, d + 1 FROM w JOIN nb ON t = src WHERE d < 15 AND t <> 50) SELECT CAST(coalesce(min(d), -1) AS BIGINT) AS hops FROM w WHERE t = 50",
    ),
    "ic13_sparse": Workload(
        "MATCH (a:Account {id: 7}), (b:Account {id: 50}) OPTIONAL MATCH p = shortestPath((a)-[:HOT_CLICK*..15]-(b)) RETURN coalesce(length(p), -1) AS hops",
        f"WITH RECURSIVE {HOT_BOTH}, w AS (SELECT 7 AS t, 0 AS d UNION SELECT dst, d + 1 FROM w JOIN hu ON t = src WHERE d < 15) SELECT coalesce(min(d), -1) AS hops FROM w WHERE t = 50",
    ),
}

_P42 = "b42 AS (SELECT DISTINCT o_custkey AS id, o_orderkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_partkey = 42)"

_MONTH = "o.date >= localdatetime('1998-07-01') AND o.date < localdatetime('1998-08-01')"
_DAYS_A = "o.date >= localdatetime('1998-01-01') AND o.date < localdatetime('1999-01-01')"
_DAYS_B = "o.date >= localdatetime('1999-01-01') AND o.date < localdatetime('2000-01-01')"

INTELLIGENCE: dict[str, Workload] = {
    "bi1": Workload(
        "MATCH (o:Order) WITH count(o) AS total MATCH (o:Order) RETURN o.date.year AS year, o.status AS status, CASE WHEN o.total < 100000 THEN 0 WHEN o.total < 200000 THEN 1 ELSE 2 END AS bucket, total, count(*) AS n, round(avg(o.total), 2) AS mean, round(100.0 * count(*) / total, 4) AS share",
        """SELECT year(o_orderdate) AS year, o_orderstatus AS status, CASE WHEN o_totalprice < 100000 THEN 0 WHEN o_totalprice < 200000 THEN 1 ELSE 2 END AS bucket, (SELECT count(*) FROM orders) AS total, count(*) AS n,
           round(avg(o_totalprice), 2) AS mean, round(CAST(100.0 * count(*) AS DOUBLE) / (SELECT count(*) FROM orders), 4) AS share FROM orders GROUP BY 1, 2, 3""",
    ),
    "bi2": Workload(
        "MATCH (p:Part)<-[:CONTAINS]-(o:Order) WHERE p.type STARTS WITH 'PROMO' AND o.date >= localdatetime('1998-01-01') AND o.date < localdatetime('1998-07-20') WITH p, sum(CASE WHEN o.date < localdatetime('1998-04-11') THEN 1 ELSE 0 END) AS a, sum(CASE WHEN o.date >= localdatetime('1998-04-11') THEN 1 ELSE 0 END) AS b RETURN p.id AS part, a, b, abs(a - b) AS diff ORDER BY diff DESC, part LIMIT 100",
        """WITH g AS (SELECT p_partkey AS part, CAST(sum(CASE WHEN o_orderdate < TIMESTAMP '1998-04-11' THEN 1 ELSE 0 END) AS BIGINT) AS a, CAST(sum(CASE WHEN o_orderdate >= TIMESTAMP '1998-04-11' THEN 1 ELSE 0 END) AS BIGINT) AS b
           FROM part JOIN lineitem ON p_partkey = l_partkey JOIN orders ON o_orderkey = l_orderkey WHERE p_type LIKE 'PROMO%' AND o_orderdate >= TIMESTAMP '1998-01-01' AND o_orderdate < TIMESTAMP '1998-07-20' GROUP BY 1) SELECT part, a, b, abs(a - b) AS diff FROM g ORDER BY diff DESC, part LIMIT 100""",
    ),
    "bi3": Workload(
        "MATCH (r:Region {name: 'ASIA'})<-[:PART_OF]-(n:Nation)<-[:LIVES_IN]-(c:Customer)<-[:STARTED_BY]-(root:Turn {turn: 0})<-[:REPLY_OF*0..]-(t:Turn {role: 'assistant'}) RETURN n.name AS nation, c.id AS customer, count(t) AS answers ORDER BY answers DESC, customer LIMIT 20",
        "SELECT n_name AS nation, c_custkey AS customer, count(*) AS answers FROM conversations JOIN customer ON conv_id = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA' AND role = 'assistant' GROUP BY 1, 2 ORDER BY answers DESC, customer LIMIT 20",
    ),
    "bi5": Workload(
        "MATCH (p:Part {id: 42})<-[:CONTAINS]-(o:Order)<-[:PLACED]-(c:Customer) WITH c, count(DISTINCT o) AS orders OPTIONAL MATCH (c)-[i:INTERACTS]->(x:Customer) WITH c, orders, count(i) AS sent OPTIONAL MATCH (c)<-[:STARTED_BY]-(t:Turn) RETURN c.id AS customer, orders, sent, count(t) AS turns, orders * 10 + sent + count(t) AS score",
        f"""WITH {TOUCH}, {_P42}, g AS (SELECT id, count(*) AS orders FROM b42 GROUP BY 1), h AS (SELECT id AS customer, orders, (SELECT count(*) FROM touch WHERE src = g.id) AS sent, (SELECT count(*) FROM conversations WHERE conv_id = g.id) AS turns FROM g)
            SELECT *, orders * 10 + sent + turns AS score FROM h""",
    ),
    "bi6": Workload(
        "MATCH (p:Part {id: 42})<-[:CONTAINS]-(:Order)<-[:PLACED]-(c:Customer) WITH DISTINCT c OPTIONAL MATCH (c)<-[i:INTERACTS]-(x:Customer) RETURN c.id AS customer, count(i) AS received, count(DISTINCT x) AS senders",
        f"WITH {TOUCH}, {_P42} SELECT b.id AS customer, count(t.id) AS received, count(DISTINCT src) AS senders FROM (SELECT DISTINCT id FROM b42) b LEFT JOIN touch t ON t.dst = b.id GROUP BY 1",
    ),
    "bi7": Workload(
        "MATCH (p:Part {id: 42})<-[:CONTAINS]-(o:Order)-[:CONTAINS]->(q:Part) WHERE o.status <> 'F' AND q.id <> 42 RETURN q.id AS part, count(*) AS n",
        "SELECT b.l_partkey AS part, count(*) AS n FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey JOIN orders ON o_orderkey = a.l_orderkey WHERE a.l_partkey = 42 AND b.l_partkey <> 42 AND o_orderstatus <> 'F' GROUP BY 1",
    ),
    "bi8": Workload(
        "MATCH (p:Part {id: 42})<-[:CONTAINS]-(o:Order)<-[:PLACED]-(c:Customer) WITH c, count(DISTINCT o) AS own OPTIONAL MATCH (c)-[:INTERACTS]-(d:Customer)-[:PLACED]->(o2:Order)-[:CONTAINS]->(q:Part {id: 42}) RETURN c.id AS customer, own, count(DISTINCT o2) AS near, own + count(DISTINCT o2) AS total",
        f"""WITH {BOTH}, {_P42}, g AS (SELECT id, count(*) AS own FROM b42 GROUP BY 1), h AS (SELECT g.id AS customer, own, count(DISTINCT o_orderkey) AS near FROM g LEFT JOIN both_ways w ON w.src = g.id LEFT JOIN b42 ON b42.id = w.dst GROUP BY 1, 2)
            SELECT *, own + near AS total FROM h""",
    ),
    "bi9": Workload(
        "MATCH (c:Customer)<-[:STARTED_BY]-(root:Turn {turn: 0})<-[:REPLY_OF*0..]-(t:Turn) RETURN c.id AS customer, count(DISTINCT root) AS threads, count(t) AS turns",
        "SELECT conv_id AS customer, count(*) FILTER (turn = 0) AS threads, count(*) AS turns FROM conversations GROUP BY 1",
    ),
    "bi10": Workload(
        """MATCH p = (c:Customer {id: 7})-[:INTERACTS*1..4]-(d:Customer) WITH d, min(length(p)) AS dist WHERE dist >= 3
           MATCH (d)-[:PLACED]->(o:Order)-[:CONTAINS]->(q:Part) WHERE q.type STARTS WITH 'PROMO' RETURN d.id AS id, dist, count(*) AS n""",
        f"""WITH RECURSIVE {NB}, w AS (SELECT 7 AS t, 0 AS d UNION SELECT dst, d + 1 FROM w JOIN nb ON t = src WHERE d < 4),
            m AS (SELECT t, min(d) AS dist FROM w GROUP BY 1 HAVING min(d) >= 3)
            SELECT t AS id, CAST(dist AS BIGINT) AS dist, count(*) AS n FROM m JOIN orders ON o_custkey = t JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON p_partkey = l_partkey WHERE p_type LIKE 'PROMO%' GROUP BY 1, 2""",
    ),
    "bi10_sparse": Workload(
        "MATCH p = (c:Customer {id: 7})-[:HOT_INTERACTS*1..4]-(d:Customer) WITH d, min(length(p)) AS dist WHERE dist >= 3 MATCH (d)-[:PLACED]->(o:Order)-[:CONTAINS]->(q:Part) WHERE q.type STARTS WITH 'PROMO' RETURN d.id AS id, dist, count(*) AS n",
        f"""WITH RECURSIVE {HOT_BOTH}, w AS (SELECT dst, 1 AS d, [id] AS used FROM hu WHERE src = 7 UNION ALL SELECT h.dst, d + 1, list_append(used, h.id) FROM w JOIN hu h ON w.dst = h.src WHERE d < 4 AND NOT list_contains(used, h.id)),
            m AS (SELECT dst, min(d) AS dist FROM w GROUP BY 1 HAVING min(d) >= 3)
            SELECT dst AS id, dist, count(*) AS n FROM m JOIN orders ON o_custkey = dst JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON p_partkey = l_partkey WHERE p_type LIKE 'PROMO%' GROUP BY 1, 2""",
    ),
    "bi11": Workload(
        """MATCH (a:Customer)-[x:CLICK]-(b:Customer)-[y:CLICK]-(c:Customer)-[z:CLICK]-(a)
           WHERE a.id < b.id AND b.id < c.id AND a.nation = b.nation AND b.nation = c.nation
             AND x.ts >= localdatetime('2024-01-03') AND y.ts >= localdatetime('2024-01-03') AND z.ts >= localdatetime('2024-01-03')
           WITH DISTINCT a, b, c RETURN a.nation AS nation, count(*) AS triangles""",
        f"""WITH {TOUCH}, k AS (SELECT DISTINCT least(src, dst) AS p, greatest(src, dst) AS q FROM touch WHERE ty = 'click' AND src <> dst AND ts >= TIMESTAMP '2024-01-03'),
            n AS (SELECT p, q, u.c_nationkey AS nation FROM k JOIN customer u ON u.c_custkey = p JOIN customer v ON v.c_custkey = q WHERE u.c_nationkey = v.c_nationkey)
            SELECT x.nation, count(*) AS triangles FROM n x JOIN n y ON x.q = y.p JOIN n z ON z.p = x.p AND z.q = y.q GROUP BY 1""",
    ),
    "bi12": Workload(
        "MATCH (c:Customer) OPTIONAL MATCH (c)-[:PLACED]->(o:Order) WHERE o.priority = '1-URGENT' AND o.total > 100000 WITH c, count(o) AS orders RETURN orders, count(*) AS customers",
        "WITH g AS (SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON o_custkey = c_custkey AND o_orderpriority = '1-URGENT' AND o_totalprice > 100000 GROUP BY 1) SELECT orders, count(*) AS customers FROM g GROUP BY 1",
    ),
    "bi13": Workload(
        f"""MATCH (z:Customer {{nation: 3}}) WHERE NOT EXISTS {{ (z)-[:PLACED]->(o:Order) WHERE {_MONTH} }}
           OPTIONAL MATCH (z)<-[i:INTERACTS]-(x:Customer)
           WITH z, i, x, EXISTS {{ (x)-[:PLACED]->(o:Order) WHERE {_MONTH} }} AS active
           WITH z.id AS id, count(i) AS received, sum(CASE WHEN x.nation = 3 AND NOT active THEN 1 ELSE 0 END) AS from_zombies
           RETURN id, received, from_zombies, CASE WHEN received = 0 THEN 0.0 ELSE round(1.0 * from_zombies / received, 4) END AS share""",
        f"""WITH {TOUCH}, zombie AS (SELECT c_custkey AS id FROM customer WHERE c_nationkey = 3 AND c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderdate >= TIMESTAMP '1998-07-01' AND o_orderdate < TIMESTAMP '1998-08-01')),
            g AS (SELECT z.id, count(t.id) AS received, count(*) FILTER (t.src IN (SELECT id FROM zombie)) AS from_zombies FROM zombie z LEFT JOIN (SELECT touch.* FROM touch JOIN customer ON src = c_custkey) t ON t.dst = z.id GROUP BY 1)
            SELECT id, received, from_zombies, CASE WHEN received = 0 THEN 0 ELSE round(CAST(from_zombies AS DOUBLE) / received, 4) END AS share FROM g""",
    ),
    "bi16": Workload(
        f"""MATCH (c:Customer)-[:PLACED]->(o:Order)-[:CONTAINS]->(:Part {{brand: 'Brand#13'}}) WHERE {_DAYS_A} WITH DISTINCT c
           CALL {{ WITH c MATCH (c)-[:INTERACTS]-(d:Customer)-[:PLACED]->(o:Order)-[:CONTAINS]->(:Part {{brand: 'Brand#13'}}) WHERE {_DAYS_A} RETURN count(DISTINCT d) AS near_a }}
           WITH c, near_a WHERE near_a <= 20
           MATCH (c)-[:PLACED]->(o:Order)-[:CONTAINS]->(:Part {{brand: 'Brand#4'}}) WHERE {_DAYS_B} WITH DISTINCT c, near_a
           CALL {{ WITH c MATCH (c)-[:INTERACTS]-(d:Customer)-[:PLACED]->(o:Order)-[:CONTAINS]->(:Part {{brand: 'Brand#4'}}) WHERE {_DAYS_B} RETURN count(DISTINCT d) AS near_b }}
           WITH c, near_a, near_b WHERE near_b <= 20 RETURN c.id AS id, near_a, near_b""",
        f"""WITH {NB}, a AS (SELECT DISTINCT o_custkey AS id FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN part ON l_partkey = p_partkey WHERE p_brand = 'Brand#13' AND o_orderdate >= TIMESTAMP '1998-01-01' AND o_orderdate < TIMESTAMP '1999-01-01'),
            b AS (SELECT DISTINCT o_custkey AS id FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN part ON l_partkey = p_partkey WHERE p_brand = 'Brand#4' AND o_orderdate >= TIMESTAMP '1999-01-01' AND o_orderdate < TIMESTAMP '2000-01-01'),
            g AS (SELECT id, (SELECT count(*) FROM nb WHERE src = id AND dst IN (SELECT id FROM a)) AS near_a, (SELECT count(*) FROM nb WHERE src = id AND dst IN (SELECT id FROM b)) AS near_b FROM a JOIN b USING (id))
            SELECT * FROM g WHERE near_a <= 20 AND near_b <= 20""",
    ),
    "bi17": Workload(
        """MATCH (a:Turn {turn: 0})-[:STARTED_BY]->(c:Customer)-[x:INTERACTS]->(m:Customer)-[y:INTERACTS]->(d:Customer)<-[:STARTED_BY]-(b:Turn {turn: 0})
           WHERE a.conv <> b.conv AND duration.days(x.ts, y.ts) >= 7
           RETURN a.conv AS a, b.conv AS b, count(DISTINCT m) AS shared ORDER BY shared DESC, a, b LIMIT 50""",
        f"""WITH {TOUCH}, root AS (SELECT conv_id FROM conversations WHERE turn = 0)
            SELECT x.src AS a, y.dst AS b, count(DISTINCT x.dst) AS shared FROM touch x JOIN touch y ON x.dst = y.src AND x.id <> y.id JOIN root p ON p.conv_id = x.src JOIN root q ON q.conv_id = y.dst JOIN customer ON c_custkey = x.dst
            WHERE x.src <> y.dst AND date_diff('day', CAST(x.ts AS DATE), CAST(y.ts AS DATE)) >= 7 GROUP BY 1, 2 ORDER BY shared DESC, a, b LIMIT 50""",
    ),
    "bi18": Workload(
        """MATCH (:Part {id: 42})<-[:CONTAINS]-(:Order)<-[:PLACED]-(a:Customer) WITH DISTINCT a
           MATCH (a)-[:INTERACTS]-(m:Customer)-[:INTERACTS]-(b:Customer) WHERE a.id <> b.id AND NOT (a)-[:INTERACTS]-(b)
           RETURN a.id AS a, b.id AS b, count(DISTINCT m) AS mutual ORDER BY mutual DESC, a, b LIMIT 20""",
        f"""WITH {NB}, {_P42}
            SELECT x.src AS a, y.dst AS b, count(DISTINCT x.dst) AS mutual FROM nb x JOIN nb y ON x.dst = y.src WHERE x.src IN (SELECT id FROM b42) AND x.src <> y.dst AND NOT EXISTS (SELECT 1 FROM nb z WHERE z.src = x.src AND z.dst = y.dst) GROUP BY 1, 2 ORDER BY mutual DESC, a, b LIMIT 20""",
    ),
}

#: state in the published run: queries that failed there
FAILED_THERE = {"is2", "is7", "ic1", "ic3", "ic10", "ic11", "ic14", "bi4", "bi10", "bi12", "bi15", "bi16", "bi17", "bi19", "bi20"}
ALL: dict[str, Workload] = MICRO | FLIGHTS | SOCIAL | SHORT | COMPLEX | INTELLIGENCE
