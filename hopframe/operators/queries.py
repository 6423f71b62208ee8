"""One query for each surrounding operator, with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from hopframe.operators.joins import asof_join, range_join, salted_join


class Tables:
    """The given tables by attribute, each opened when it is asked for."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir

    def __getattr__(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.sf_dir}/{name}.parquet")

    def sql(self, text: str, *tables: str) -> DataFrame:
        return self.spark.sql(text, **{t: getattr(self, t) for t in tables})


Body = Callable[[Tables], DataFrame]
OPS: dict[str, tuple[Body, str]] = {}


def op(name: str, sql: str) -> Callable[[Body], Body]:
    def put(body: Body) -> Body:
        OPS[name] = (body, sql)
        return body

    return put


def row(name: str, body: Body, sql: str) -> None:
    OPS[name] = (body, sql)


c = F.col


def _k():
    return F.get_json_object("props", "$.k").cast("long")


_KS = "CAST(json_extract_string(props, '$.k') AS BIGINT)"
_DAY = "date_trunc('day', {0})"

# --- sources in place
row("src_parquet_scan", lambda t: t.lineitem.agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("s")), "SELECT count(*) AS n, round(sum(l_extendedprice), 2) AS s FROM lineitem")
row("src_parquet_pruned", lambda t: t.lineitem.where("l_quantity > 49").select("l_orderkey", "l_quantity"), "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 49")
row("catalog_view", lambda t: (t.orders.createOrReplaceTempView("orders_in_place"), t.spark.table("orders_in_place").groupBy("o_orderpriority").count().withColumnRenamed("count", "n"))[1], "SELECT o_orderpriority, count(*) AS n FROM orders GROUP BY 1")
row("sink_view", lambda t: (t.orders.groupBy("o_custkey").agg(F.count("*").alias("n")).createOrReplaceTempView("order_counts"), t.spark.sql("SELECT n, count(*) AS customers FROM order_counts GROUP BY n"))[1], "SELECT n, count(*) AS customers FROM (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) GROUP BY 1")

# --- projection and predicates
row("proj_expr", lambda t: t.lineitem.select("l_orderkey", "l_linenumber", F.round(c("l_extendedprice") * (1 - c("l_discount")), 4).alias("net")), "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
row("proj_rename", lambda t: t.nation.select(c("n_nationkey").alias("id"), c("n_name").alias("name")), "SELECT n_nationkey AS id, n_name AS name FROM nation")
row("proj_distinct", lambda t: t.lineitem.select("l_returnflag", "l_linestatus").distinct(), "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem")
row("filt_range", lambda t: t.orders.where("o_orderdate >= '1997-01-01' and o_orderdate < '1997-02-01'").select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_orderdate >= '1997-01-01' AND o_orderdate < '1997-02-01'")
row("filt_in", lambda t: t.orders.where(c("o_orderpriority").isin("1-URGENT", "2-HIGH")).select("o_orderkey", "o_orderpriority"), "SELECT o_orderkey, o_orderpriority FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH')")
row("filt_like", lambda t: t.part.where(c("p_type").like("PROMO%")).select("p_partkey"), "SELECT p_partkey FROM part WHERE p_type LIKE 'PROMO%'")
row("filt_rlike", lambda t: t.customer.where(c("c_name").rlike("00[1-3]$")).select("c_name"), "SELECT c_name FROM customer WHERE regexp_matches(c_name, '00[1-3]$')")
row("filt_null_3vl", lambda t: t.labels.select("doc_id", F.when(c("toxic") == 1, c("quality")).alias("q")).where(~(c("q") == 1) | c("q").isNull()).select("doc_id"), "SELECT doc_id FROM (SELECT doc_id, CASE WHEN toxic = 1 THEN quality END AS q FROM labels) WHERE NOT (q = 1) OR q IS NULL")
row("filt_compound", lambda t: t.part.where("(p_size between 10 and 20 and p_brand <> 'Brand#11') or p_retailprice > 1900").select("p_partkey"), "SELECT p_partkey FROM part WHERE (p_size BETWEEN 10 AND 20 AND p_brand <> 'Brand#11') OR p_retailprice > 1900")

# --- joins
_OC = "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey"
for _name, _hint in (("join_hash_broadcast", "broadcast"), ("join_sort_merge", "merge"), ("join_shuffle_hash", "shuffle_hash")):
    row(_name, lambda t, h=_hint: t.orders.join(t.customer.hint(h), c("o_custkey") == c("c_custkey")).select("o_orderkey", "c_name"), _OC)
row("join_left", lambda t: t.customer.join(t.orders.where("o_totalprice > 400000"), c("c_custkey") == c("o_custkey"), "left").select("c_custkey", "o_orderkey"), "SELECT c_custkey, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey AND o_totalprice > 400000")
row("join_right", lambda t: t.orders.where("o_totalprice > 400000").join(t.customer, c("c_custkey") == c("o_custkey"), "right").select("c_custkey", "o_orderkey"), "SELECT c_custkey, o_orderkey FROM (SELECT * FROM orders WHERE o_totalprice > 400000) RIGHT JOIN customer ON c_custkey = o_custkey")
row("join_full", lambda t: t.customer.join(t.orders, c("c_custkey") == c("o_custkey"), "full").select("c_custkey", "o_orderkey"), "SELECT c_custkey, o_orderkey FROM customer FULL JOIN orders ON c_custkey = o_custkey")
row("join_semi", lambda t: t.documents.join(t.labels.where("toxic = 1"), "doc_id", "left_semi").select("doc_id", "lang"), "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)")
row("join_anti", lambda t: t.documents.join(t.labels, "doc_id", "left_anti").select("doc_id", "lang"), "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
row("join_cross", lambda t: t.nation.crossJoin(t.region).select("n_name", "r_name"), "SELECT n_name, r_name FROM nation CROSS JOIN region")
row("join_theta", lambda t: t.nation.alias("a").join(t.nation.alias("b"), (c("a.n_regionkey") == c("b.n_regionkey")) & (c("a.n_nationkey") < c("b.n_nationkey"))).select(c("a.n_name").alias("a"), c("b.n_name").alias("b")), "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
row("join_self", lambda t: t.conversations.alias("a").join(t.conversations.alias("b"), (c("a.conv_id") == c("b.conv_id")) & (c("b.turn") == c("a.turn") + 1)).select(c("a.conv_id"), c("a.turn"), c("a.role").alias("asks"), c("b.role").alias("answers")), "SELECT a.conv_id, a.turn, a.role AS asks, b.role AS answers FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1")
row("join_composite", lambda t: t.lineitem.select("l_orderkey", "l_linenumber").join(t.lineitem.groupBy("l_orderkey", "l_linenumber").agg(F.count("*").alias("n")), ["l_orderkey", "l_linenumber"]), "SELECT l_orderkey, l_linenumber, count(*) OVER (PARTITION BY l_orderkey, l_linenumber) AS n FROM lineitem")
row("join_nullsafe", lambda t: t.nation.select(F.when(c("n_nationkey") > 4, c("n_nationkey")).alias("k"), "n_name").join(t.nation.select(F.when(c("n_nationkey") > 20, c("n_nationkey")).alias("j"), c("n_name").alias("m")), c("k").eqNullSafe(c("j"))).select("n_name", "m"), "SELECT a.n_name, b.n_name AS m FROM nation a JOIN nation b ON CASE WHEN a.n_nationkey > 4 THEN a.n_nationkey END IS NOT DISTINCT FROM CASE WHEN b.n_nationkey > 20 THEN b.n_nationkey END")
row("join_salted", lambda t: salted_join(t.events.select("event_id", _k().alias("k")), t.customer.select(c("c_custkey").alias("k"), "c_name"), "k", 8, c("event_id")).select("event_id", "c_name"), f"SELECT event_id, c_name FROM events JOIN customer ON c_custkey = {_KS}")
_DAYS = "datediff(o_orderdate, date '1995-01-01')"
row("join_range_dates", lambda t: range_join(t.orders.select("o_orderkey", F.expr(_DAYS).alias("day")), t.spark.range(10).select(c("id").alias("w"), (c("id") * 200).alias("lo"), (c("id") * 200 + 30).alias("hi")), "day", "lo", "hi", 30.0).groupBy("w").agg(F.count("*").alias("n")), "SELECT w, count(*) AS n FROM orders JOIN (SELECT range AS w, range * 200 AS lo, range * 200 + 30 AS hi FROM range(10)) ON date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) >= lo AND date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) < hi GROUP BY 1")
row("join_interval_events", lambda t: range_join(t.events.where("event_type = 'purchase'").select(c("event_id").alias("p"), F.unix_micros(c("ts").cast("timestamp")).alias("at")), t.events.where("event_type = 'click' and value > 100").select(c("event_id").alias("k"), F.unix_micros(c("ts").cast("timestamp")).alias("lo"), (F.unix_micros(c("ts").cast("timestamp")) + 3_600_000_000).alias("hi")), "at", "lo", "hi", 3.6e9).groupBy("k").agg(F.count("*").alias("n")), "SELECT b.event_id AS k, count(*) AS n FROM events a JOIN events b ON a.ts >= b.ts AND a.ts < b.ts + INTERVAL 1 HOUR WHERE a.event_type = 'purchase' AND b.event_type = 'click' AND b.value > 100 GROUP BY 1")
row("join_asof_event_order", lambda t: asof_join(t.events.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), t.events.where("event_type = 'click'").select("user_id", "ts", c("event_id").alias("click")), "user_id", "ts", "click", "click").select("event_id", "click"), "SELECT a.event_id, b.event_id AS click FROM (SELECT * FROM events WHERE event_type = 'purchase') a ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click' QUALIFY row_number() OVER (PARTITION BY user_id, ts ORDER BY event_id DESC) = 1) b ON a.user_id = b.user_id AND a.ts >= b.ts")

# --- aggregation
row("agg_group", lambda t: t.lineitem.groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("q"), F.count("*").alias("n"), F.round(F.avg("l_discount"), 6).alias("d")), "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q, count(*) AS n, round(avg(l_discount), 6) AS d FROM lineitem GROUP BY 1, 2")
row("agg_global", lambda t: t.lineitem.agg(F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi"), F.count("*").alias("n")), "SELECT min(l_quantity) AS lo, max(l_quantity) AS hi, count(*) AS n FROM lineitem")
row("agg_having", lambda t: t.orders.groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 15"), "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 15")
row("agg_filter_clause", lambda t: t.orders.groupBy("o_orderpriority").agg(F.count_if(c("o_orderstatus") == "F").alias("f"), F.expr("count(*) FILTER (WHERE o_orderstatus = 'O')").alias("o")), "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o FROM orders GROUP BY 1")
row("agg_distinct", lambda t: t.lineitem.groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")), "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
row("agg_stats", lambda t: t.lineitem.groupBy("l_linestatus").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_quantity"), 6).alias("v"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r")), "SELECT l_linestatus, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_quantity), 6) AS v, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem GROUP BY 1")
row("agg_percentile", lambda t: t.events.groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("p50"), F.round(F.percentile("value", 0.9), 6).alias("p90")), "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY 1")
row("agg_approx_distinct", lambda t: t.lineitem.agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("e")).select((F.abs(c("a") - c("e")) <= 0.1 * c("e")).alias("close")), "SELECT true AS close")
row("agg_mode", lambda t: t.documents.groupBy("source").agg(F.count("*").alias("n")).agg(F.max_by("source", F.struct("n", "source")).alias("source")), "SELECT source FROM documents GROUP BY 1 ORDER BY count(*) DESC, source DESC LIMIT 1")
row("agg_minmax_by", lambda t: t.orders.groupBy("o_orderpriority").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("cheapest")), "SELECT o_orderpriority, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY 1")
row("agg_collect_list", lambda t: t.orders.groupBy("o_custkey").agg(F.concat_ws(",", F.sort_array(F.collect_list("o_orderkey")).cast("array<string>")).alias("ids")), "SELECT o_custkey, string_agg(CAST(o_orderkey AS VARCHAR), ',' ORDER BY o_orderkey) AS ids FROM orders GROUP BY 1")
row("agg_collect_set", lambda t: t.orders.groupBy("o_custkey").agg(F.concat_ws(",", F.sort_array(F.collect_set("o_orderstatus"))).alias("s")), "SELECT o_custkey, string_agg(DISTINCT o_orderstatus, ',' ORDER BY o_orderstatus) AS s FROM orders GROUP BY 1")
row("agg_grouping_sets", lambda t: t.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())", "lineitem"), "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")
row("agg_cube", lambda t: t.lineitem.cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")), "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
row("agg_rollup", lambda t: t.lineitem.rollup("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("q")), "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
row("agg_pivot", lambda t: t.orders.groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey")).fillna(0), "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS \"F\", count(*) FILTER (o_orderstatus = 'O') AS \"O\", count(*) FILTER (o_orderstatus = 'P') AS \"P\" FROM orders GROUP BY 1")

# --- windows


def _by():
    return W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


def _ev():
    return W.partitionBy("user_id").orderBy("ts", "event_id")


_BYS = "(PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"
for _name, _f, _s in (
    ("win_row_number", lambda: F.row_number().over(_by()), f"row_number() OVER {_BYS}"),
    ("win_ntile", lambda: F.ntile(4).over(_by()), f"ntile(4) OVER {_BYS}"),
    ("win_percent_rank", lambda: F.round(F.percent_rank().over(_by()), 6), f"round(percent_rank() OVER {_BYS}, 6)"),
    ("win_cume_dist", lambda: F.round(F.cume_dist().over(_by()), 6), f"round(cume_dist() OVER {_BYS}, 6)"),
):
    row(_name, lambda t, f=_f: t.orders.select("o_orderkey", f().alias("v")), f"SELECT o_orderkey, {_s} AS v FROM orders")
row("win_rank_dense", lambda t: t.part.select("p_partkey", F.rank().over(W.partitionBy("p_brand").orderBy("p_size")).alias("r"), F.dense_rank().over(W.partitionBy("p_brand").orderBy("p_size")).alias("d")), "SELECT p_partkey, rank() OVER w AS r, dense_rank() OVER w AS d FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
_EVS = "(PARTITION BY user_id ORDER BY ts, event_id)"
row("win_lag_lead", lambda t: t.events.select("event_id", F.lag("value").over(_ev()).alias("before"), F.lead("value").over(_ev()).alias("after")), f"SELECT event_id, lag(value) OVER {_EVS} AS before, lead(value) OVER {_EVS} AS after FROM events")
row("win_first_last", lambda t: t.events.select("event_id", F.first("value").over(_ev()).alias("f"), F.last("value").over(_ev().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("l")), f"SELECT event_id, first_value(value) OVER {_EVS} AS f, last_value(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS l FROM events")
row("win_nth", lambda t: t.events.select("event_id", F.nth_value("value", 3).over(_ev()).alias("v")), f"SELECT event_id, nth_value(value, 3) OVER {_EVS} AS v FROM events")
row("win_rows_frame", lambda t: t.events.select("event_id", F.round(F.avg("value").over(_ev().rowsBetween(-2, 0)), 6).alias("v")), "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS v FROM events")
row("win_range_frame", lambda t: t.part.select("p_partkey", F.count("*").over(W.partitionBy("p_brand").orderBy("p_size").rangeBetween(-5, 5)).alias("n")), "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS n FROM part")
row("win_running_total", lambda t: t.orders.select("o_orderkey", F.round(F.sum("o_totalprice").over(_by().rowsBetween(W.unboundedPreceding, 0)), 2).alias("v")), "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS v FROM orders")

# --- order and limits
row("sort_multi_nulls", lambda t: t.labels.select("doc_id", F.when(c("toxic") == 1, c("quality")).alias("q")).orderBy(c("q").desc_nulls_first(), c("doc_id")), "SELECT doc_id, CASE WHEN toxic = 1 THEN quality END AS q FROM labels ORDER BY q DESC NULLS FIRST, doc_id")
row("topk_global", lambda t: t.orders.orderBy(c("o_totalprice").desc(), "o_orderkey").select("o_orderkey", "o_totalprice").limit(10), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
row("topk_per_group", lambda t: t.orders.withColumn("r", F.row_number().over(W.partitionBy("o_orderpriority").orderBy(c("o_totalprice").desc(), "o_orderkey"))).where("r <= 3").select("o_orderpriority", "o_orderkey", "r"), "SELECT o_orderpriority, o_orderkey, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders QUALIFY r <= 3")
row("limit_offset", lambda t: t.orders.orderBy("o_orderkey").select("o_orderkey").offset(100).limit(20), "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 20 OFFSET 100")

# --- sets
_A, _B = (lambda t: t.customer.select(c("c_nationkey").alias("k"))), (lambda t: t.supplier.select(c("s_nationkey").alias("k")))
_AS, _BS = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier"
row("set_union_all", lambda t: _A(t).unionAll(_B(t)), f"{_AS} UNION ALL {_BS}")
row("set_union", lambda t: _A(t).union(_B(t)).distinct(), f"{_AS} UNION {_BS}")
row("set_union_by_name", lambda t: t.customer.select(c("c_name").alias("name"), c("c_custkey").alias("id")).unionByName(t.supplier.select(c("s_suppkey").alias("id"), c("s_name").alias("name"))), "SELECT c_name AS name, c_custkey AS id FROM customer UNION ALL BY NAME SELECT s_suppkey AS id, s_name AS name FROM supplier")
row("set_intersect", lambda t: _A(t).intersect(_B(t)), f"{_AS} INTERSECT {_BS}")
row("set_intersect_all", lambda t: _A(t).intersectAll(_B(t)), f"{_AS} INTERSECT ALL {_BS}")
row("set_except", lambda t: t.events.select(c("user_id").alias("k")).subtract(t.events.where("value > 50").select(_k().alias("k"))), f"SELECT user_id AS k FROM events EXCEPT SELECT {_KS} FROM events WHERE value > 50")
row("set_except_all", lambda t: _A(t).exceptAll(_B(t)), f"{_AS} EXCEPT ALL {_BS}")


def both(name: str, text: str, *tables: str, duck: str | None = None) -> None:
    """An operator whose SQL is the same in both engines."""
    braced = text
    for x in tables:
        for word in ("FROM ", "JOIN "):
            braced = braced.replace(f"{word}{x}", f"{word}{{{x}}}")
    row(name, lambda t: t.sql(braced, *tables), duck or text)


# --- subqueries
both("sub_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT 1.9 * avg(o_totalprice) FROM orders)", "orders")
both("sub_in", "SELECT c_custkey FROM customer WHERE c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 2)", "customer", "nation")
both("sub_exists", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o_totalprice > 450000)", "customer", "orders")
both("sub_correlated", "SELECT c_custkey, (SELECT max(o_totalprice) FROM orders o WHERE o.o_custkey = c.c_custkey) AS most FROM customer c", "customer", "orders")
both("sub_lateral", "SELECT c_custkey, n FROM customer c, LATERAL (SELECT count(*) AS n FROM orders o WHERE o.o_custkey = c.c_custkey AND o_orderstatus = 'P')", "customer", "orders")
both("cte", "WITH s AS (SELECT o_custkey, sum(o_totalprice) AS total FROM orders GROUP BY o_custkey), m AS (SELECT avg(total) AS mean FROM s) SELECT o_custkey FROM s, m WHERE total > 1.5 * mean", "orders")
_LEVELS = " MAX RECURSION LEVEL 10000"  # Spark stops at 100 otherwise
_YEARS = f"""WITH RECURSIVE y AS (SELECT row_number() OVER (ORDER BY y NULLS FIRST) AS i, y, n FROM (SELECT year(o_orderdate) AS y, count(*) AS n FROM orders GROUP BY 1)),
    w(i, y, n, total){_LEVELS} AS (SELECT i, y, n, n FROM y WHERE i = 1 UNION ALL SELECT y.i, y.y, y.n, w.total + y.n FROM w JOIN y ON y.i = w.i + 1) SELECT y, n, total FROM w"""
both("cte_recursive", _YEARS, "orders", duck=_YEARS.replace(_LEVELS, ""))

# --- strings
row("str_basic", lambda t: t.customer.select("c_custkey", F.upper("c_mktsegment").alias("u"), F.length("c_name").alias("n"), F.substring("c_name", 10, 3).alias("s"), F.lpad(c("c_custkey").cast("string"), 6, "0").alias("p"), F.replace("c_name", F.lit("Customer"), F.lit("C")).alias("r")), "SELECT c_custkey, upper(c_mktsegment) AS u, length(c_name) AS n, substring(c_name, 10, 3) AS s, lpad(CAST(c_custkey AS VARCHAR), 6, '0') AS p, replace(c_name, 'Customer', 'C') AS r FROM customer")
row("str_regex", lambda t: t.customer.select("c_custkey", F.regexp_extract("c_name", "#0*([1-9][0-9]*)$", 1).alias("d"), F.regexp_replace("c_name", "[0-9]", "x").alias("x")), "SELECT c_custkey, regexp_extract(c_name, '#0*([1-9][0-9]*)$', 1) AS d, regexp_replace(c_name, '[0-9]', 'x', 'g') AS x FROM customer")
row("str_split_explode", lambda t: t.pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1)).alias("href")), """SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS href FROM pages""")
row("str_url", lambda t: t.pages.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host")), "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host FROM pages")
row("str_hash", lambda t: t.documents.select("doc_id", F.sha2(c("text").cast("binary"), 256).alias("s"), F.md5(c("text").cast("binary")).alias("m")), "SELECT doc_id, sha256(text) AS s, md5(text) AS m FROM documents")
row("str_same_text", lambda t: t.documents.groupBy(F.sha2(c("text").cast("binary"), 256).alias("h")).agg(F.count("*").alias("n"), F.min("doc_id").alias("first")).where("n > 1").select("first", "n"), "SELECT min(doc_id) AS first, count(*) AS n FROM documents GROUP BY text HAVING count(*) > 1")
row("str_levenshtein", lambda t: t.nation.alias("a").join(t.nation.alias("b"), c("a.n_nationkey") < c("b.n_nationkey")).select(c("a.n_name").alias("a"), c("b.n_name").alias("b"), F.levenshtein("a.n_name", "b.n_name").alias("d")), "SELECT a.n_name AS a, b.n_name AS b, levenshtein(a.n_name, b.n_name) AS d FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey")

# --- time
row("dt_extract", lambda t: t.events.select("event_id", F.year("ts").alias("y"), F.month("ts").alias("m"), F.day("ts").alias("d"), F.hour("ts").alias("h")), "SELECT event_id, year(ts) AS y, month(ts) AS m, day(ts) AS d, hour(ts) AS h FROM events")
row("dt_trunc", lambda t: t.events.groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("n")), "SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS n FROM events GROUP BY 1")
row("dt_diff", lambda t: t.orders.select("o_orderkey", F.datediff(F.lit("2001-01-01").cast("date"), "o_orderdate").alias("d")), "SELECT o_orderkey, date_diff('day', CAST(o_orderdate AS DATE), DATE '2001-01-01') AS d FROM orders")
row("dt_interval", lambda t: t.orders.where("o_orderdate + interval 3 months > '2001-09-01'").select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_orderdate + INTERVAL 3 MONTH > '2001-09-01'")

# --- numbers
row("math_basic", lambda t: t.lineitem.select("l_orderkey", "l_linenumber", F.round(F.sqrt("l_quantity"), 6).alias("q"), F.abs(c("l_quantity") - 25).alias("a"), F.round(F.ln("l_extendedprice"), 6).alias("l"), F.pmod(c("l_partkey"), F.lit(7)).alias("m")), "SELECT l_orderkey, l_linenumber, round(sqrt(l_quantity), 6) AS q, abs(l_quantity - 25) AS a, round(ln(l_extendedprice), 6) AS l, l_partkey % 7 AS m FROM lineitem")
row("math_round_div", lambda t: t.part.select("p_partkey", F.try_divide(c("p_size"), c("p_size") - 10).alias("d")).select("p_partkey", F.round("d", 6).alias("d")), "SELECT p_partkey, round(CAST(p_size AS DOUBLE) / nullif(p_size - 10, 0), 6) AS d FROM part")
row("math_bucket", lambda t: t.part.groupBy(F.floor(c("p_retailprice") / 100).alias("b")).agg(F.count("*").alias("n")), "SELECT CAST(floor(p_retailprice / 100) AS BIGINT) AS b, count(*) AS n FROM part GROUP BY 1")

# --- arrays, maps, JSON


def _tenths(first: int):
    """The finite ones of 32 components, in tenths rounded down."""
    finite = F.filter(F.slice("embedding", first, 32), lambda x: F.abs(x) < float("inf"))
    return F.transform(finite, lambda x: F.floor(x.cast("double") * 10))


_TENTHS = "list_transform(list_filter(embedding[{0}:{1}], lambda x: abs(x) < 'inf'), lambda x: CAST(floor(CAST(x AS DOUBLE) * 10) AS BIGINT))"
row("arr_hof", lambda t: t.embeddings.select("vec_id", F.round(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x), F.lit(0.0), lambda a, x: a + x), 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive")), "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 4) AS norm2, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
row("arr_explode_pos", lambda t: t.embeddings.select("vec_id", F.posexplode("embedding").alias("i", "x")).select("vec_id", "i", F.round(c("x").cast("double"), 5).alias("x")), "SELECT vec_id, i - 1 AS i, round(CAST(embedding[i] AS DOUBLE), 5) AS x FROM embeddings, range(1, 65) r(i)")
row("arr_set_ops", lambda t: t.embeddings.select("vec_id", F.array_intersect(_tenths(1), _tenths(33)).alias("x")).select("vec_id", F.size("x").alias("n")), f"SELECT vec_id, len(list_intersect({_TENTHS.format(1, 32)}, {_TENTHS.format(33, 64)})) AS n FROM embeddings")
row("arr_dot", lambda t: t.embeddings.where("vec_id = 0").select(c("embedding").alias("q")).crossJoin(t.embeddings).select("vec_id", F.round(F.aggregate(F.zip_with("q", "embedding", lambda a, b: a.cast("double") * b), F.lit(0.0), lambda a, x: a + x), 4).alias("dot")), "SELECT vec_id, round(list_dot_product(CAST(embedding AS DOUBLE[]), CAST((SELECT embedding FROM embeddings WHERE vec_id = 0) AS DOUBLE[])), 4) AS dot FROM embeddings")
row("map_build", lambda t: t.nation.groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m")).select("n_regionkey", F.size("m").alias("n"), F.try_element_at("m", F.lit(3)).alias("three")), "SELECT n_regionkey, count(*) AS n, max(CASE WHEN n_nationkey = 3 THEN n_name END) AS three FROM nation GROUP BY 1")
row("json_extract", lambda t: t.events.select("event_id", _k().alias("k")), f"SELECT event_id, {_KS} AS k FROM events")
row("json_roundtrip", lambda t: t.events.select("event_id", F.from_json(F.to_json(F.struct("user_id", "value")), "user_id long, value double").alias("x")).select("event_id", "x.user_id", "x.value"), "SELECT event_id, user_id, value FROM events")


def _run(body: Body):
    return lambda spark, sf_dir: body(Tables(spark, sf_dir))


QUERIES = {k: _run(body) for k, (body, _) in OPS.items()}
ORACLES = {k: sql for k, (_, sql) in OPS.items()}
