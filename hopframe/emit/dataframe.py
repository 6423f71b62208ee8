"""A relational plan as a DataFrame."""

from __future__ import annotations

from collections.abc import Callable
from typing import assert_never

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hopframe.emit.sqltext import Dialect, Writer
from hopframe.lang import ast as A
from hopframe.plan import rel as R


def to_dataframe(spark: SparkSession, rel: R.Rel, table: Callable[[str], DataFrame], iterated: Callable[[R.Iterate], DataFrame]) -> DataFrame:
    """``table`` gives the base tables, ``iterated`` runs a path iteration."""
    writer = Writer(Dialect.SPARK)

    def text(e) -> str:
        return writer.expr(e)

    def build(r: R.Rel) -> DataFrame:
        match r:
            case R.Table(name):
                return table(name)
            case R.Iterate():
                return iterated(r)
            case R.Union(parts, every):
                out = build(parts[0])
                for p in parts[1:]:
                    out = out.union(build(p))
                return out if every else out.distinct()
            case R.Select():
                return select(r)
            case _ as never:
                assert_never(never)

    def select(s: R.Select) -> DataFrame:
        df = build(s.source).alias(s.alias) if s.source is not None else spark.range(1).select(F.lit(1).alias("one"))
        for j in s.joins:
            other = build(j.rel).alias(j.alias)
            if j.on:
                df = df.join(other, F.expr(" AND ".join(text(c) for c in j.on)), j.kind if j.kind != "cross" else "inner")
            else:
                df = df.join(other, F.lit(True), "left") if j.kind == "left" else df.crossJoin(other)
        for c in s.where:
            df = df.where(F.expr(text(c)))
        if s.group is None and any(_aggregates(e) for e, _ in s.columns):
            df = df.agg(*(F.expr(text(e)).alias(n) for e, n in s.columns))
        elif s.group is not None:
            named = {repr(g): f"group{i}" for i, g in enumerate(s.group)}
            rest = [(e, n) for e, n in s.columns if repr(e) not in named]
            sums = [F.expr(text(e)).alias(n) for e, n in rest]
            grouped = df.groupBy(*(F.expr(text(g)).alias(named[repr(g)]) for g in s.group))
            df = grouped.agg(*sums) if sums else df.select(*(F.expr(text(g)).alias(named[repr(g)]) for g in s.group)).distinct()
            df = df.select(*(F.col(named[repr(e)]).alias(n) if repr(e) in named else F.col(f"`{n}`") for e, n in s.columns))
        else:
            df = df.select(*(F.expr(text(e)).alias(n) for e, n in s.columns)) if s.columns else df.select(F.lit(1).alias("one"))
        if s.distinct:
            df = df.distinct()
        if s.order:
            df = df.orderBy(*(F.col(f"`{n}`").desc_nulls_first() if d else F.col(f"`{n}`").asc_nulls_last() for n, d in s.order))
        if s.offset is not None:
            df = df.offset(_number(s.offset))
        if s.limit is not None:
            df = df.limit(_number(s.limit))
        return df

    return build(rel)


def _number(e) -> int:
    if isinstance(e, A.Lit) and isinstance(e.value, int):
        return e.value
    raise ValueError("SKIP and LIMIT take whole numbers")


def _aggregates(e) -> bool:
    from hopframe.plan.compile import aggregated

    return aggregated(e)
