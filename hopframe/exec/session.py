"""Graph queries on a Spark session, over tables where they are."""

from __future__ import annotations

import json
import re
from dataclasses import dataclass
from typing import Any

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hopframe.catalog.model import GraphMap
from hopframe.emit.dataframe import to_dataframe
from hopframe.emit.sqltext import Dialect, to_sql
from hopframe.lang.parser import QuerySyntaxError, parse
from hopframe.paths import forms
from hopframe.plan import rel as R
from hopframe.plan.compile import Compiler, walk

#: row counts by application, source and table; they decide the order of joins only
_ROWS: dict[tuple[str, str, str], int] = {}

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def walked(it: R.Iterate, link: DataFrame, seeds: DataFrame, pairs: DataFrame | None) -> DataFrame:
    """Runs one path iteration."""
    match it.mode:
        case "forest":
            return forms.ancestors(link, seeds, it.keys, it.lo, it.hi)
        case "reach":
            return forms.reach(link, seeds, it.keys, it.lo, it.hi, it.ids, it.undirected)
        case "trail":
            return forms.trails(link, seeds, it.keys, it.lo, it.hi, it.ids)
        case "shortest" if not it.traced:
            found = forms.reach(link, seeds, it.keys, 0, it.hi, it.ids) if pairs is None else forms.between(link, pairs, it.keys, it.hi)
            return found.where(F.col("hops") >= it.lo)
        case "shortest" | "all shortest":
            return forms.shortest_paths(link, seeds, it.keys, it.lo, it.hi, it.ids, pairs, it.mode == "all shortest")
    raise ValueError(f"no iteration {it.mode!r}")


@dataclass(frozen=True)
class Trace:
    """What each stage made of a query."""

    ast: Any
    profiles: list
    plan: R.Rel
    sql: str


class GraphSession:
    """Compiles queries against a map and runs them where the session's data is.

    ``source`` is a folder of Parquet tables or None for the session's own catalog (views, warehouse tables, a
    remote session). Only the tables a query touches are opened.
    """

    def __init__(self, spark: SparkSession, gmap: GraphMap | None = None, source: str | None = None):
        self.spark, self.gmap, self.source = spark, gmap or GraphMap.commerce(), source
        self.stats: dict[str, int] = {}
        self._tables: dict[str, DataFrame] = {}
        self._used: set[str] = set()  # names that stand for other tables than the source's
        self._kinds: dict[tuple[str, str], str | None] = {}

    @staticmethod
    def local(source: str, gmap: GraphMap | None = None) -> GraphSession:
        """In-process mode over files."""
        spark = SparkSession.builder.master("local[*]").config("spark.ui.enabled", "false").getOrCreate()
        return GraphSession(spark, gmap, source)

    def table(self, name: str) -> DataFrame:
        if name not in self._tables:
            self._tables[name] = self.spark.read.parquet(f"{self.source}/{name}.parquet") if self.source and name in TABLES else self.spark.table(name)
        return self._tables[name]

    def kind(self, table: str, column: str) -> str | None:
        """Whether a table's column holds whole numbers, text or something else; None where the table cannot be seen."""
        if (table, column) not in self._kinds:
            try:
                name = next((f.dataType.typeName() for f in self.table(table).schema.fields if f.name == column), None)
            except AnalysisException:
                name = None
            self._kinds[table, column] = None if name is None else "integer" if name in ("byte", "short", "integer", "long") else "text" if name == "string" else "other"
        return self._kinds[table, column]

    def use(self, name: str, df: DataFrame) -> None:
        """Puts a DataFrame in the place of a table."""
        self._kinds = {k: v for k, v in self._kinds.items() if k[0] != name}
        self._tables[name] = df
        self._used.add(name)

    def analyze(self) -> dict[str, int]:
        """Row counts of all mapped tables, which anchors are then chosen by. Reads Parquet footers only."""
        names = {n.table for n in self.gmap.nodes.values() if n.table} | {e.table for e in self.gmap.edges.values() if e.table}
        self.stats = {n: self.table(n).count() for n in sorted(names)}
        return self.stats

    def rows(self, name: str) -> int | None:
        """A table's row count from Parquet footers, read once for an application; None for other tables not analysed."""
        if name in self.stats:
            return self.stats[name]
        if not self.source or name not in TABLES or name in self._used:
            return None
        place = (self.spark.conf.get("spark.app.id"), self.source, name)
        if place not in _ROWS:
            _ROWS[place] = self.table(name).count()
        return _ROWS[place]

    def compiled(self, text: str, **params: Any) -> tuple[Compiler, R.Rel]:
        compiler = Compiler(self.gmap, params, self.stats, self.kind, self.rows)
        return compiler, compiler.query(parse(text))

    def cypher(self, text: str, **params: Any) -> DataFrame:
        """The query's result."""
        return self.run(self.compiled(text, **params)[1])

    def graph_table(self, text: str, **params: Any) -> DataFrame:
        """``GRAPH_TABLE (graph MATCH pattern [WHERE ...] COLUMNS (...))``: the SQL form of a pattern query."""
        m = re.fullmatch(r"\s*GRAPH_TABLE\s*\(\s*(\w+)\s+(MATCH\b.*?)\bCOLUMNS\s*\((.*)\)\s*\)\s*;?\s*", text, re.DOTALL | re.IGNORECASE)
        if not m or m[1] != self.gmap.name:
            raise QuerySyntaxError(f"expected GRAPH_TABLE ({self.gmap.name} MATCH ... COLUMNS (...))")
        return self.cypher(f"{m[2]} RETURN {m[3]}", **params)

    def run(self, plan: R.Rel) -> DataFrame:
        done: dict[R.Iterate, DataFrame] = {}

        def iterated(it: R.Iterate) -> DataFrame:
            if it not in done:
                link, seeds, pairs = (None if x is None else to_dataframe(self.spark, x, self.table, iterated) for x in (it.link, it.seeds, it.pairs))
                done[it] = walked(it, link, seeds, pairs)
            return done[it]

        return to_dataframe(self.spark, plan, self.table, iterated)

    def translate(self, text: str, dialect: str = "spark", **params: Any) -> str:
        """SQL text only; nothing runs."""
        return to_sql(self.compiled(text, **params)[1], Dialect[dialect.upper()])

    def sql(self, text: str, **params: Any) -> DataFrame:
        """The query by way of its SQL text. Path iterations run first and are read as views."""
        plan = self.compiled(text, **params)[1]
        views: dict[R.Iterate, str] = {}
        for it in [x for x in walk(plan) if isinstance(x, R.Iterate)]:
            if it not in views:
                views[it] = f"hopframe_path_{len(views)}_{abs(hash(it)) % 10**8}"
                self.run(it).createOrReplaceTempView(views[it])
        for name in {x.name for x in walk(plan) if isinstance(x, R.Table)}:
            self.table(name).createOrReplaceTempView(name)
        return self.spark.sql(to_sql(plan, Dialect.SPARK, views))

    def stages(self, text: str, **params: Any) -> Trace:
        compiler, plan = self.compiled(text, **params)
        return Trace(parse(text), compiler.profiles, plan, to_sql(plan, Dialect.SPARK))

    def materialize(self, name: str, df: DataFrame, path: str | None = None) -> DataFrame:
        """Keeps an intermediate result as a view, or as Parquet at ``path`` behind the view."""
        if path is not None:
            df.write.mode("overwrite").parquet(path)
            df = self.spark.read.parquet(path)
        df.createOrReplaceTempView(name)
        return df

    def describe(self) -> str:
        """The graph's labels, types and properties as JSON, for tools and agents."""
        nodes = {n.label: {"key": list(n.key), "access": n.access.value, "properties": sorted(n.props)} for n in self.gmap.nodes.values()}
        edges = [{"type": e.type, "from": e.source.label, "to": e.target.label, "access": e.access.value, "properties": sorted(e.props)} for e in self.gmap.edges.values()]
        return json.dumps({"graph": self.gmap.name, "nodes": nodes, "relationships": edges}, sort_keys=True)

    def expand(self, label: str, seed: int, hops: int, edge: str) -> DataFrame:
        """Distinct nodes within ``hops`` of a seed over one relationship type, with their least distance."""
        query = f"MATCH p = (a:{label} {{id: $seed}})-[:{edge}*1..{hops}]->(b:{label}) RETURN b.id AS id, min(length(p)) AS hops"
        return self.cypher(query, seed=seed)

    def retrieve(self, edge: str, label: str, seeds: list[int], hops: int, limit_per_hop: int) -> DataFrame:
        """Retrieval for language models: rows of each hop around the seeds, the smallest ids first."""
        from pyspark.sql import Window as W

        found = self.cypher(f"MATCH p = (a:{label})-[:{edge}*1..{hops}]->(b:{label}) WHERE a.id IN $seeds RETURN b.id AS id, min(length(p)) AS hops", seeds=seeds)
        return found.withColumn("rank", F.row_number().over(W.partitionBy("hops").orderBy("id"))).where(F.col("rank") <= limit_per_hop)
