"""Sinks are written, read back and joined."""

from hopframe.sources.files import bucketed, sink_bucketed

SF_DIR = "/root/testdata/sf0.001"


def test_sink_bucketed_runs_and_runs_again(spark):
    orders = spark.read.parquet(f"{SF_DIR}/orders.parquet")
    for _ in range(2):  # each run has tables of its own
        assert sum(r["n"] for r in sink_bucketed(spark, SF_DIR).collect()) == orders.where("o_custkey is not null").count()


def test_bucketed_tables_join_without_exchange(spark):
    a = bucketed(spark.range(1000).selectExpr("id % 50 AS k", "id AS a"), 4, "k")
    b = bucketed(spark.range(50).selectExpr("id AS k", "id * 2 AS b"), 4, "k")
    joined = a.join(b.hint("merge"), "k")
    assert joined.count() == 1000 and joined.where("b <> 2 * (a % 50)").count() == 0
    assert "Exchange" not in joined._jdf.queryExecution().executedPlan().toString()
