"""Queries that made their data up read a given table."""

from datetime import datetime

import duckdb
import pytest

from hopframe.workloads.registry import ORACLES, QUERIES

SF_DIR = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name, table", [("arr_set_ops", "embeddings"), ("cte_recursive", "orders"), ("ds_graphmap", "events")])
def test_reads_a_given_table(spark, name, table):
    got = QUERIES[name](spark, SF_DIR)
    assert got.count() > 0
    assert [f.removeprefix("file://") for f in got.inputFiles()] == [f"{SF_DIR}/{table}.parquet"]


def same(spark, folder, name, table):
    got = QUERIES[name](spark, str(folder))
    with duckdb.connect() as duck:
        duck.execute(f"CREATE VIEW {table} AS SELECT * FROM '{folder}/{table}.parquet/*.parquet'")
        assert sorted(map(tuple, got.collect()), key=str) == sorted(duck.execute(ORACLES[name]).fetchall(), key=str)


def test_arrays_with_odd_components(spark, tmp_path):
    nan, inf = float("nan"), float("inf")
    rows = [(1, [0.5, -0.04, nan, inf, 0.05]), (2, None), (3, []), (4, [None, 0.1] * 32), (5, [nan if i % 11 == 0 else (i % 9) / 10 - 0.3 for i in range(70)]), (6, [-0.0] * 32 + [0.0] * 32)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    same(spark, tmp_path, "arr_set_ops", "embeddings")


def test_recursion_over_missing_years(spark, tmp_path):
    """Years without orders and orders without a date do not end it."""
    years = [None, None, 1990, 1992, 1992, 1850]
    rows = [(i, y and datetime(y, 7, 1)) for i, y in enumerate(years)]
    spark.createDataFrame(rows, "o_orderkey long, o_orderdate timestamp").write.parquet(str(tmp_path / "orders.parquet"))
    assert QUERIES["cte_recursive"](spark, str(tmp_path)).count() == 4
    same(spark, tmp_path, "cte_recursive", "orders")


def test_catalog_rows_and_types_without_events(spark, tmp_path):
    events = spark.read.parquet(f"{SF_DIR}/events.parquet")
    events.where("event_type in ('click', 'error')").write.parquet(str(tmp_path / "events.parquet"))
    same(spark, tmp_path, "ds_graphmap", "events")
    counted = spark.read.format("graphmap").load().groupBy("kind", "access").count()
    assert {tuple(r) for r in counted.collect()} == {("node", "own", 11), ("node", "inlined", 3), ("node", "implied", 5), ("edge", "key", 9), ("edge", "separate", 10), ("edge", "typed", 9)}
