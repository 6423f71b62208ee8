"""Counting without expanding: walks are counted by degree products and corrected for repeated edges."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, replace
from itertools import combinations
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopframe.lang import ast as A
from hopframe.plan import rel as R


def walk_counts(link: DataFrame, hops: int, seeds: DataFrame | None = None) -> DataFrame:
    """(node, walks): number of walks of ``hops`` edges that end at each node, one aggregation a hop."""
    ends = link.select(F.col("s0").alias("node"), F.col("t0").alias("next"))
    level = (ends.select("node").distinct() if seeds is None else seeds.select(F.col("s0").alias("node")).distinct()).withColumn("walks", F.lit(1).cast("long"))
    for _ in range(hops):
        level = level.join(ends, "node").groupBy(F.col("next").alias("node")).agg(F.sum("walks").alias("walks"))
    return level


def two_hop_count(link: DataFrame, seeds: DataFrame | None = None) -> DataFrame:
    """Edge-unique chains of two edges: sum over middle nodes of in- times out-degree, less each loop with itself."""
    first = link if seeds is None else link.join(seeds.select("s0").distinct(), "s0", "left_semi")
    ins = first.groupBy(F.col("t0").alias("m")).agg(F.count("*").alias("i"))
    outs = link.groupBy(F.col("s0").alias("m")).agg(F.count("*").alias("o"))
    walks = ins.join(outs, "m").agg(F.coalesce(F.sum(F.col("i") * F.col("o")), F.lit(0)).alias("walks"))
    loops = first.where("s0 = t0").agg(F.count("*").alias("loops"))
    return walks.crossJoin(loops).select((F.col("walks") - F.col("loops")).alias("n"))  # one row each


def three_hop_count(link: DataFrame, seeds: DataFrame) -> DataFrame:
    """Edge-unique chains of three edges from the seeds, by inclusion and exclusion over equal edges."""
    first = link.join(seeds.select("s0").distinct(), "s0", "left_semi")
    outs = link.groupBy(F.col("s0").alias("m")).agg(F.count("*").alias("o"))
    loops = link.where("s0 = t0").groupBy(F.col("s0").alias("m")).agg(F.count("*").alias("k"))
    walks = walk_counts(link, 3, seeds).agg(F.coalesce(F.sum("walks"), F.lit(0)).alias("w"))
    same12 = first.where("s0 = t0").join(outs, F.col("t0") == F.col("m")).agg(F.coalesce(F.sum("o"), F.lit(0)).alias("a"))
    same23 = first.join(loops, F.col("t0") == F.col("m")).agg(F.coalesce(F.sum("k"), F.lit(0)).alias("b"))
    back = link.groupBy(F.col("s0").alias("t0"), F.col("t0").alias("s0")).agg(F.count("*").alias("r"))
    same13 = first.join(back, ["s0", "t0"]).agg(F.coalesce(F.sum("r"), F.lit(0)).alias("c"))
    all3 = first.where("s0 = t0").agg(F.count("*").alias("d"))
    row = walks.crossJoin(same12).crossJoin(same23).crossJoin(same13).crossJoin(all3)  # one row each
    return row.select((F.col("w") - F.col("a") - F.col("b") - F.col("c") + 2 * F.col("d")).alias("n"))


# --- the same inside a compiled query

#: pairs of hops that may take the same edge, up to which their repeats are counted apart
MOST_REPEATS = 3


@dataclass(frozen=True)
class FlatJoin:
    """A pattern as one flat join: sources by alias, conditions, and the pairs of rows that must differ.

    ``unlike`` holds (alias, alias, equalities) of rows of one table; ``keys`` the tables' unique columns.
    """

    sources: tuple[tuple[str, Any], ...]
    conds: tuple[Any, ...]
    unlike: tuple[tuple[str, str, tuple[Any, ...]], ...]
    keys: tuple[tuple[str, tuple[str, ...]], ...]


def aliases(e: Any) -> set[str]:
    if isinstance(e, tuple | list):
        return set().union(*map(aliases, e))
    if isinstance(e, R.Col):
        return {e.alias}
    return set().union(*(aliases(getattr(e, f)) for f in getattr(e, "__dataclass_fields__", ())))


def _over(e: Any, old: str, new: str) -> Any:
    """``e`` over the row ``new`` in place of ``old``."""
    if isinstance(e, tuple):
        return tuple(_over(x, old, new) for x in e)
    if isinstance(e, R.Col):
        return replace(e, alias=new) if e.alias == old else e
    fields = getattr(e, "__dataclass_fields__", ())
    return replace(e, **{f: _over(getattr(e, f), old, new) for f in fields}) if fields else e


def _pairs(conds: Iterable[Any]) -> dict[frozenset[str], list[tuple[Any, Any]]] | None:
    """Equalities by the two sources they join, or None if a condition over several sources is none."""
    out: dict[frozenset[str], list[tuple[Any, Any]]] = {}
    for c in conds:
        if len(aliases(c)) < 2:
            continue
        sides = [aliases(x) for x in c.args] if isinstance(c, A.Call) and c.name == "=" else []
        if len(sides) != 2 or any(len(x) != 1 for x in sides):
            return None
        out.setdefault(frozenset(sides[0] | sides[1]), []).append(c.args)
    return out


def factored_count(flat: FlatJoin) -> R.Select | None:
    """``count(*)`` of the join as column n without its rows: sums of products of counts, side by side.

    Where rows must differ, inclusion and exclusion over the equal ones counts them apart. None where the conditions
    form a circle, or where every join is a look-up by a unique key, so that nothing is gained.
    """
    sources, pairs = dict(flat.sources), _pairs(flat.conds)
    if not pairs or len(flat.unlike) > MOST_REPEATS or all(_looked_up(flat, sources, p, on) for p, on in pairs.items()):
        return None
    terms: dict[tuple[str, ...], int] = {}
    for size in range(len(flat.unlike) + 1):
        for equal in combinations(flat.unlike, size):
            stands = {a: a for a in sources}  # which row stands for a row that it equals
            for a, b, _ in equal:
                stands = {x: stands[a] if y == stands[b] else y for x, y in stands.items()}
            kept = tuple(stands.values())
            terms[kept] = terms.get(kept, 0) + (-1) ** size
    parts = []
    for kept, times in terms.items():
        if not times:
            continue
        merged = flat.conds
        for a, into in zip(sources, kept):
            merged = merged if a == into else _over(merged, a, into)
        merged = tuple(A.Call("is not null", (c.args[0],)) if isinstance(c, A.Call) and c.name == "=" and c.args[0] == c.args[1] else c for c in merged)
        one = _tree_count({a: sources[a] for a in dict.fromkeys(kept)}, tuple(dict.fromkeys(merged)))
        if one is None:
            return None
        parts.append(R.Select(one, columns=((A.Call("*", (R.Col("c", "n", "integer"), A.Lit(times))), "n"),)))
    return R.Select(R.Union(tuple(parts)), columns=((A.Call("as long", (A.Call("sum", (R.Col("c", "n", "integer"),)),)), "n"),))


def _looked_up(flat: FlatJoin, sources: dict[str, Any], pair: frozenset[str], on: list[tuple[Any, Any]]) -> bool:
    """Whether one side of the join has at most one row for each of the other's."""
    for a in pair:
        columns = tuple(sorted(x.name for args in on for x in args if isinstance(x, R.Col) and x.alias == a))
        if isinstance(sources[a], R.Table) and any(t == sources[a].name and set(key) <= set(columns) for t, key in flat.keys):
            return True
    return False


def _tree_count(sources: dict[str, Any], conds: tuple[Any, ...]) -> R.Select | None:
    """(n): rows of a join whose conditions form a tree. Both sides of its middle are summed before they meet."""
    pairs = _pairs(conds) or {}
    own = {a: tuple(c for c in conds if aliases(c) == {a}) for a in sources}
    near = {a: [next(iter(p - {a})) for p in pairs if a in p] for a in sources}
    first = next(iter(sources))

    def side(a: str, without: str | None) -> set[str]:
        found, todo = {a}, [a]
        while todo:
            at = todo.pop()
            more = [x for x in near[at] if x not in found and {at, x} != {a, without}]
            found.update(more)
            todo += more
        return found

    if len(pairs) != len(sources) - 1 or side(first, None) != set(sources) or any(not aliases(c) for c in conds):
        return None

    def columns(a: str, b: str) -> list[Any]:
        return [x if aliases(x) == {a} else y for x, y in pairs[frozenset({a, b})]]

    def summed(a: str, toward: str) -> R.Select:
        """Rows of a's side by the columns that join it to the other side."""
        joins, weight = [], None
        for b in near[a]:
            if b != toward:
                on = tuple(A.Call("=", (x, R.Col(f"w_{b}", f"k{i}"))) for i, x in enumerate(columns(a, b)))
                joins.append(R.Join("inner", summed(b, a), f"w_{b}", on))
                one = R.Col(f"w_{b}", "w", "integer")
                weight = one if weight is None else A.Call("*", (weight, one))
        total = A.Call("count", (A.Lit("*"),)) if weight is None else A.Call("as long", (A.Call("sum", (weight,)),))
        keys = columns(a, toward)
        return R.Select(sources[a], a, tuple(joins), own[a], (*((x, f"k{i}") for i, x in enumerate(keys)), (total, "w")), tuple(dict.fromkeys(keys)))

    if not pairs:
        return R.Select(sources[first], first, where=own[first], columns=((A.Call("count", (A.Lit("*"),)), "n"),))
    a, b = min((tuple(sorted(p)) for p in pairs), key=lambda p: abs(2 * len(side(p[0], p[1])) - len(sources)))
    on = tuple(A.Call("=", (R.Col("l", f"k{i}"), R.Col("r", f"k{i}"))) for i in range(len(columns(a, b))))
    product = A.Call("*", (R.Col("l", "w", "integer"), R.Col("r", "w", "integer")))
    return R.Select(summed(a, b), "l", (R.Join("inner", summed(b, a), "r", on),), columns=((A.Call("as long", (A.Call("sum", (product,)),)), "n"),))
