"""Checks of a map against the data."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hopframe.catalog.model import NodeAccess
from hopframe.emit.sqltext import Dialect, Writer
from hopframe.lang.ast import Call, Var
from hopframe.lang.parser import parse_expression
from hopframe.plan import rel as R


@dataclass(frozen=True)
class Finding:
    kind: str
    entry: str
    detail: str


def column(text: str) -> Column:
    """A catalog entry's expression as a Spark column."""

    def over(e):
        return R.Col("", e.name) if isinstance(e, Var) else Call(e.name, tuple(over(a) for a in e.args)) if isinstance(e, Call) else e

    return F.expr(Writer(Dialect.SPARK).expr(over(parse_expression(text))))


def names_in(text: str) -> set[str]:
    def found(e) -> set[str]:
        return {e.name} if isinstance(e, Var) else set().union(*map(found, e.args)) if isinstance(e, Call) else set()

    return found(parse_expression(text))


def validate(session, deep: bool = False) -> list[Finding]:
    """Columns exist, types of a name are told apart; with ``deep`` also keys, inclusion, and keyless link tables.

    Deep checks count on the cluster; the driver gets one number for each entry.
    """
    gmap, out = session.gmap, []
    for n in gmap.nodes.values():
        if n.table and (missing := {c for t in (*n.key, *n.props.values()) for c in names_in(t)} - set(session.table(n.table).columns)):
            out.append(Finding("missing column", n.label, ", ".join(sorted(missing))))
        if n.access is not NodeAccess.OWN and not n.via:
            out.append(Finding("unreachable label", n.label, "no entry inlines or implies it"))
    for e in gmap.edges.values():
        texts = [*e.source.cols, *e.target.cols, *e.props.values(), *([e.where] if e.where else []), *([e.type_column] if e.type_column else []), *(c for c in e.edge_key if c != "*")]
        if missing := {c for t in texts for c in names_in(t)} - set(session.table(e.table).columns):
            out.append(Finding("missing column", e.name, ", ".join(sorted(missing))))
    by_type: dict[tuple[str, str], set[str]] = {}
    for e in gmap.edges.values():
        by_type.setdefault((e.type, e.source.label), set()).add(e.target.label)
    out += [Finding("several endpoint labels", t, f"{s} to {', '.join(sorted(x))}") for (t, s), x in by_type.items() if len(x) > 1]
    if deep:
        out += [Finding(r["kind"], r["entry"], str(r["rows"])) for r in deep_checks(session).where("rows > 0").collect()]
    return out


def deep_checks(session) -> DataFrame:
    """(kind, entry, rows): repeated node keys, edges without their endpoint, repeated whole rows of keyless links."""
    gmap, parts = session.gmap, []

    def counted(kind: str, entry: str, df: DataFrame) -> None:
        parts.append(df.agg(F.count("*").alias("rows")).select(F.lit(kind).alias("kind"), F.lit(entry).alias("entry"), "rows"))

    for n in gmap.nodes.values():
        if n.table:
            keys = [column(k).alias(f"k{i}") for i, k in enumerate(n.key)]
            counted("repeated key", n.label, session.table(n.table).groupBy(*keys).count().where("count > 1"))
    for e in gmap.edges.values():
        rows = session.table(e.table)
        rows = rows.where(column(e.where)) if e.where else rows
        for side, end in (("from", e.source), ("to", e.target)):
            n = gmap.nodes[end.label]
            if n.access is NodeAccess.OWN and (e.owner != end.label or end.cols != n.key) and e.included:
                ends = rows.select(*(column(c).alias(f"k{i}") for i, c in enumerate(end.cols))).where(reduce(Column.__and__, [F.col(f"k{i}").isNotNull() for i in range(len(end.cols))]))
                known = session.table(n.table).select(*(column(k).alias(f"k{i}") for i, k in enumerate(n.key)))
                counted("edge without its node", f"{e.name}.{side}", ends.join(known, [f"k{i}" for i in range(len(n.key))], "left_anti"))
        if e.edge_key == ("*",) and e.owner is None:
            counted("repeated rows of a keyless link", e.name, rows.groupBy(*rows.columns).count().where("count > 1"))
    return reduce(DataFrame.unionAll, parts)
