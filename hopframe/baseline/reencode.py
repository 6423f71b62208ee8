"""The same data copied into generic node and edge tables with a property blob, on the same engine."""

from __future__ import annotations

import time
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopframe.catalog.model import EdgeAccess, EdgeMap, End, GraphMap, NodeAccess, NodeMap
from hopframe.exec.session import GraphSession
from hopframe.exec.staging import staged

ACCESS = {"bigint": "int", "int": "int", "double": "float", "string": "text", "timestamp_ntz": "time"}


@dataclass(frozen=True)
class Reencoded:
    """A session over the copy, and what making it cost."""

    session: GraphSession
    seconds: float
    rows: int


def _blob(columns: list[str], kind: str):
    if kind == "map":
        pairs = [x for c in columns for x in (F.lit(c), F.col(f"p_{c}").cast("string"))]
        return F.create_map(*pairs) if pairs else F.create_map().cast("map<string,string>")
    return F.to_json(F.struct(*(F.col(f"p_{c}").alias(c) for c in columns))) if columns else F.lit("{}")


def _identity(label: str, column: str, df: DataFrame):
    kind = df.schema[column].dataType
    parts = [F.col(f"{column}.{f}") for f in kind.fieldNames()] if hasattr(kind, "fieldNames") else [F.col(column)]
    return F.concat_ws(":", F.lit(label), *(p.cast("string") for p in parts))


def reencode(session: GraphSession, edges: list[str], blob: str = "json", layout: str = "generic") -> Reencoded:
    """Copies the named entries and their endpoint labels. ``layout`` 'per_label' makes a typed table for each.

    The copies are written to the shared folder; the map over them has standard patterns only.
    """
    gmap, start = session.gmap, time.perf_counter()
    chosen = [gmap.edges[e] for e in edges]
    labels = list(dict.fromkeys(x for e in chosen for x in (e.source.label, e.target.label)))
    copies: dict[str, list[DataFrame]] = {"nodes": [], "edges": []}
    typed: dict[str, DataFrame] = {}
    new_nodes: dict[str, NodeMap] = {}
    new_edges: dict[str, EdgeMap] = {}

    def reader(name: str, kind: str) -> str:
        if layout == "per_label":
            return f"p_{name}"
        return f"{'map' if blob == 'map' else 'json'}_{ACCESS.get(kind, 'text')}(props, '{name if blob == 'map' else '$.' + name}')"

    for label in labels:
        props = sorted(gmap.nodes[label].props)
        df = session.cypher(f"MATCH (n:{label}) RETURN id(n) AS k" + "".join(f", n.{p} AS p_{p}" for p in props))
        kinds = {p: df.schema[f"p_{p}"].dataType.simpleString() for p in props}
        wide = df.select(_identity(label, "k", df).alias("id"), *(f"p_{p}" for p in props))
        table = "nodes" if layout == "generic" else f"node_{label}"
        if layout == "generic":
            copies["nodes"].append(wide.select("id", F.lit(label).alias("label"), _blob(props, blob).alias("props")))
        else:
            typed[table] = wide
        new_nodes[label] = NodeMap(label, NodeAccess.OWN, ("id",), table, {p: reader(p, kinds[p]) for p in props}, (), f"label = '{label}'" if layout == "generic" else None)
    for e in chosen:
        props = sorted(e.props)
        a, b = e.source.label, e.target.label
        only = GraphSession(session.spark, replace(gmap, edges={e.name: e}), session.source)
        only._tables = session._tables
        df = only.cypher(f"MATCH (a:{a})-[r:{e.type}]->(b:{b}) RETURN id(a) AS s, id(b) AS t" + "".join(f", r.{p} AS p_{p}" for p in props))
        kinds = {p: df.schema[f"p_{p}"].dataType.simpleString() for p in props}
        wide = df.select(F.concat_ws("#", F.lit(e.name), F.monotonically_increasing_id().cast("string")).alias("id"), _identity(a, "s", df).alias("src"), _identity(b, "t", df).alias("dst"), *(f"p_{p}" for p in props))
        table = "edges" if layout == "generic" else f"edge_{e.name}"
        if layout == "generic":
            copies["edges"].append(wide.select("id", "src", "dst", F.lit(e.name).alias("type"), _blob(props, blob).alias("props")))
        else:
            typed[table] = wide
        new_edges[e.name] = EdgeMap(e.type, EdgeAccess.TYPED if layout == "generic" else EdgeAccess.SEPARATE, End(a, ("src",)), End(b, ("dst",)), table, None, None, "type" if layout == "generic" else None, e.name if layout == "generic" else None, ("id",), {p: reader(p, kinds[p]) for p in props}, included=False, name=e.name)
    for table, parts in copies.items():
        if parts:
            out = parts[0]
            for p in parts[1:]:
                out = out.unionByName(p)
            typed[table] = out
    again = GraphSession(session.spark, GraphMap(f"{gmap.name}_copy", new_nodes, new_edges), None)
    rows = 0
    for table, df in typed.items():
        kept = staged(df)
        rows += kept.count()
        again.use(table, kept)
    return Reencoded(again, time.perf_counter() - start, rows)


def reified_lines(session: GraphSession) -> GraphSession:
    """The three-way junction rows as nodes of their own, each with three binary edges."""
    lines = session.table("lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity").withColumn("line_id", F.monotonically_increasing_id())
    raw = {
        "graph": "reified",
        "nodes": {"Line": {"access": "own", "table": "reified_line", "key": ["line_id"], "props": {"quantity": "l_quantity"}}, **{x: {"access": "own", "table": t, "key": [k], "props": {"id": k, "name": n}} for x, t, k, n in (("Order", "orders", "o_orderkey", "o_orderstatus"), ("Part", "part", "p_partkey", "p_name"), ("Supplier", "supplier", "s_suppkey", "s_name"))}},
        "edges": {x: {"access": "key", "owner": "Line", "from": {"label": "Line", "cols": ["line_id"]}, "to": {"label": y, "cols": [c]}, "acyclic": True} for x, y, c in (("OF_ORDER", "Order", "l_orderkey"), ("OF_PART", "Part", "l_partkey"), ("OF_SUPPLIER", "Supplier", "l_suppkey"))},
    }
    out = GraphSession(session.spark, GraphMap.from_dict(raw), session.source)
    out.use("reified_line", staged(lines))
    return out


def uncoupled(gmap: GraphMap) -> GraphMap:
    """The map without the declaration that two relationship types share rows: the naive self-join."""
    return gmap.with_edge("SOURCED_FROM", same_row_as=None)
