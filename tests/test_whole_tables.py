"""Queries over whole tables leave no row out."""

from hopframe.workloads.registry import QUERIES

SF_DIR = "/root/testdata/sf0.001"


def rows(spark, name):
    return spark.read.parquet(f"{SF_DIR}/{name}.parquet")


def test_whole_table_queries(spark):
    orders, customers = rows(spark, "orders"), rows(spark, "customer")
    got = QUERIES["join_full"](spark, SF_DIR)
    assert got.where("o_orderkey is not null").count() == orders.count()
    assert got.where("c_custkey is not null").select("c_custkey").distinct().count() == customers.count()
    assert QUERIES["agg_collect_list"](spark, SF_DIR).count() == orders.select("o_custkey").distinct().count()
    assert QUERIES["arr_explode_pos"](spark, SF_DIR).select("vec_id").distinct().count() == rows(spark, "embeddings").count()
    assert QUERIES["sort_multi_nulls"](spark, SF_DIR).count() == rows(spark, "labels").count()


def test_vertex_programs_over_all_events(spark):
    events = rows(spark, "events").selectExpr("user_id AS a", "CAST(get_json_object(props, '$.k') AS BIGINT) AS b")
    nodes = events.select("a").union(events.select("b")).distinct().count()
    for name in ("algo_pagerank", "algo_wcc"):
        assert QUERIES[name](spark, SF_DIR).count() == nodes
    assert QUERIES["algo_sssp"](spark, SF_DIR).where("t0 <> 7 and hops = 1").count() == events.where("a = 7 and b <> 7").select("b").distinct().count()
