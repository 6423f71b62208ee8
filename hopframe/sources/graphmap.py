"""The graph catalog as a data source: ``spark.read.format("graphmap").load(path)``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader

from hopframe.catalog.model import GraphMap


class GraphMapSource(DataSource):
    """Rows (kind, name, source, target, access, properties, type_column, type_value) of a mapping catalog."""

    @classmethod
    def name(cls) -> str:
        return "graphmap"

    def schema(self) -> str:
        return "kind string, name string, source string, target string, access string, properties int, type_column string, type_value string"

    def reader(self, schema) -> DataSourceReader:
        return GraphMapReader(self.options.get("path"))


class GraphMapReader(DataSourceReader):
    def __init__(self, path: str | None):
        gmap = GraphMap.load(path) if path else GraphMap.commerce()
        self.rows = [("node", n.label, None, None, n.access.value, len(n.props), None, None) for n in gmap.nodes.values()]
        self.rows += [("edge", e.type, e.source.label, e.target.label, e.access.value, len(e.props), e.type_column, None if e.type_value is None else str(e.type_value)) for e in gmap.edges.values()]

    def read(self, partition):
        yield from self.rows


def ds_graphmap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows and distinct actors of every relationship that the catalog tells by the type of an event."""
    spark.dataSource.register(GraphMapSource)
    typed = spark.read.format("graphmap").load().where("kind = 'edge' and type_column = 'event_type'")
    found = spark.read.parquet(f"{sf_dir}/events.parquet").groupBy("event_type").agg(F.count("*").alias("n"), F.count_distinct("user_id").alias("actors"))
    rows = typed.join(found, F.col("type_value") == F.col("event_type"), "left")
    return rows.select("name", "source", "target", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("actors", F.lit(0)).alias("actors"))


QUERIES = {"ds_graphmap": ds_graphmap}
_TYPED = [(t.upper(), "Customer", "Customer", t) for t in ("click", "view", "purchase", "signup", "error")] + [("ACTED", "Actor", "Account", t) for t in ("click", "view")]
ORACLES = {"ds_graphmap": f"SELECT name, source, target, count(event_id) AS n, count(DISTINCT user_id) AS actors FROM (VALUES {', '.join(map(str, _TYPED))}) v(name, source, target, of_type) LEFT JOIN events ON event_type = of_type GROUP BY name, source, target, of_type"}
