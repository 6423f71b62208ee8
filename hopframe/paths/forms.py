"""Path iterations as DataFrame loops.

A link is a table of s0.., t0.. (source and target identity) and e0.. (edge identity); seeds have s0... The results
have s0.., t0.. and hops. Rounds are written to the shared folder, so lineage stays short and nothing but the size of
the last level comes to the driver; while that level is small, one job does several rounds.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hopframe.exec.staging import dropped, replaced, staged

#: rounds of a trail enumeration without an upper bound
TRAIL_ROUNDS = 64
#: rounds after which a search for ends or distances gives up with an error
REACH_ROUNDS = 10_000
#: rows of a level up to which one job does ``SMALL_ROUNDS`` rounds
SMALL_ROWS, SMALL_ROUNDS = 10_000, 3
#: bounded searches up to this many hops are one plan without rounds
FLAT_HOPS = 6
#: rounds of walking up a forest from few seeds before doubling takes over
CLIMB_ROUNDS = 18


class PathLimit(RuntimeError):
    """A path iteration without a bound went on for too long."""


def _names(keys: int) -> tuple[list[str], list[str]]:
    return [f"s{i}" for i in range(keys)], [f"t{i}" for i in range(keys)]


def _equal(left: list[str], right: list[str]) -> Column:
    return reduce(Column.__and__, [F.col(a) == F.col(b) for a, b in zip(left, right)])


def _start(seeds: DataFrame, s: list[str], t: list[str]) -> DataFrame:
    return seeds.select(*s).distinct().select(*s, *(F.col(a).alias(b) for a, b in zip(s, t)), F.lit(0).cast("long").alias("hops"))


def edge_text(ids: int) -> Column:
    """An edge's identity as one string: the key itself, or all parts with their bars escaped and nulls told apart."""
    if ids == 1:
        return F.col("e0").cast("string")
    parts = [F.coalesce(F.replace(F.replace(F.col(f"e{i}").cast("string"), F.lit("\\"), F.lit("\\\\")), F.lit("|"), F.lit("\\|")), F.lit("\\N")) for i in range(ids)]
    return F.concat_ws("|", *parts)


def _hop(edges: DataFrame, s: list[str], t: list[str], ids: int = 0) -> DataFrame:
    """The link under names that do not clash: f0.., g0.. and, if asked for, edge."""
    edge = [edge_text(ids).alias("edge")] if ids else []
    return edges.select(*(F.col(a).alias(f"f{i}") for i, a in enumerate(s)), *(F.col(b).alias(f"g{i}") for i, b in enumerate(t)), *edge)


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _one_on(level: DataFrame, hop: DataFrame, s: list[str], t: list[str], depth: int, labels: bool) -> DataFrame:
    """The distinct ends one hop further. ``labels``: with the least first edge that leads there."""
    on = _equal(t, [f"f{i}" for i in range(len(s))])
    ends = [*(F.col(a) for a in s), *(F.col(f"g{i}").alias(b) for i, b in enumerate(t))]
    hops = F.lit(depth).cast("long").alias("hops")
    joined = level.join(hop, on)
    if not labels:
        return joined.select(*ends).distinct().select(*s, *t, hops)
    first = F.col("edge") if depth == 1 else F.col("first")
    return joined.select(*ends, first.alias("first")).groupBy(*s, *t).agg(F.min("first").alias("first")).select(*s, *t, hops, "first")


def reach(link: DataFrame, seeds: DataFrame, keys: int = 1, lo: int = 1, hi: int | None = None, ids: int = 1, undirected: bool = False, until: DataFrame | None = None) -> DataFrame:
    """Every (source, target) once, with its least number of hops; ``lo`` is 0 or 1.

    A source itself is reached with ``lo`` 1 only over a path that comes back without taking an edge twice. In a
    link that holds each edge in both directions (``undirected``) this is the shortest cycle, which joins two branches
    of the search: ends therefore carry the first edge that leads there. ``until`` (s0.., t0..) ends the search once
    all these pairs are reached. Without ``hi``, PathLimit is raised rather than end early.
    """
    if lo > 1:
        raise ValueError("reach keeps the least number of hops; paths of two hops and more need trails")
    s, t = _names(keys)
    labels = undirected and lo == 1
    start = _start(seeds, s, t)
    start = start.withColumn("first", F.lit(None).cast("string")) if labels else start
    flat = hi is not None and hi <= FLAT_HOPS and until is None
    edges = link if flat else staged(link)
    hop = _hop(edges, s, t, ids if labels else 0)
    if flat:
        level, levels = start, [start] if lo == 0 or labels else []
        for depth in range(1, hi + 1):
            level = _one_on(level, hop, s, t, depth, labels)
            levels.append(level)
        if not levels:
            return start.where("false")
        every = _union(levels)
        if labels:
            best = every.groupBy(*s, *t).agg(F.min(F.struct("hops", "first")).alias("best")).select(*s, *t, "best.hops", "best.first")
        else:
            best = every.groupBy(*s, *t).agg(F.min("hops").alias("hops"))
    else:
        best = _levels(start, hop, s, t, lo, hi, labels, until)
    return _with_cycles(best, hop, s, t, hi) if labels else best


def _levels(start: DataFrame, hop: DataFrame, s: list[str], t: list[str], lo: int, hi: int | None, labels: bool, until: DataFrame | None) -> DataFrame:
    """The search's levels, a round or a few in each job."""
    most = REACH_ROUNDS + 1 if hi is None else hi
    front = staged(start)
    levels = [front] if lo == 0 or labels else []
    depth, rows = 0, front.count()
    while depth < most and rows:
        new: list[DataFrame] = []
        for _ in range(min(SMALL_ROUNDS if rows <= SMALL_ROWS else 1, most - depth)):
            depth += 1
            near = _one_on(new[-1] if new else front, hop, s, t, depth, labels)
            if levels + new:
                near = near.join(_union(levels + new).select(*s, *t), [*s, *t], "left_anti")
            new.append(near.select(*start.columns))
        found = staged(_union(new))
        front = found.where(F.col("hops") == depth)
        rows = front.count()
        if hi is None and depth > REACH_ROUNDS and not found.where(F.col("hops") > REACH_ROUNDS).isEmpty():
            raise PathLimit(f"new ends appear after {REACH_ROUNDS} hops; give an upper bound")
        levels.append(found)
        if len(levels) > 8:  # fold the levels, so that the plan stays small
            levels = [staged(_union(levels))]
        if until is not None and until.join(_union(levels).select(*s, *t), [*s, *t], "left_anti").isEmpty():
            break
    return _union(levels) if levels else front.where("false")


def _with_cycles(best: DataFrame, hop: DataFrame, s: list[str], t: list[str], hi: int | None) -> DataFrame:
    """Ends with, for every source on a cycle, the length of its shortest; sources without one go."""
    apart = ~_equal(s, t)
    u = best.select(*s, *(F.col(x).alias(f"f{i}") for i, x in enumerate(t)), F.col("hops").alias("hops_u"), F.col("first").alias("first_u"))
    v = best.select(*s, *(F.col(x).alias(f"g{i}") for i, x in enumerate(t)), F.col("hops").alias("hops_v"), F.col("first").alias("first_v"))
    met = u.join(hop, [f"f{i}" for i in range(len(s))]).join(v, [*s, *(f"g{i}" for i in range(len(s)))])
    branches = F.when((F.col("hops_u") == 0) & (F.col("hops_v") == 0), F.lit(True)).when(F.col("hops_u") == 0, F.col("edge") != F.col("first_v")).when(F.col("hops_v") == 0, F.lit(False)).otherwise(F.col("first_u") != F.col("first_v"))
    cycles = met.where(branches).groupBy(*s).agg(F.min(F.col("hops_u") + F.col("hops_v") + 1).alias("hops"))
    cycles = cycles if hi is None else cycles.where(F.col("hops") <= hi)
    return best.where(apart).select(*s, *t, "hops").unionByName(cycles.select(*s, *(F.col(a).alias(b) for a, b in zip(s, t)), "hops"))


def trails(link: DataFrame, seeds: DataFrame, keys: int = 1, lo: int = 1, hi: int | None = None, ids: int = 1) -> DataFrame:
    """A row for every path that repeats no edge: s0.., t0.., hops, the edges used and the nodes passed, both in order.

    Without ``hi``, PathLimit is raised after ``TRAIL_ROUNDS`` rounds.
    """
    s, t = _names(keys)
    hop = _hop(staged(link), s, t, ids)
    at = F.col(t[0]) if keys == 1 else F.struct(*(F.col(b).alias(f"k{i}") for i, b in enumerate(t)))
    to = F.col("g0") if keys == 1 else F.struct(*(F.col(f"g{i}").alias(f"k{i}") for i in range(keys)))
    start = _start(seeds, s, t)
    front = staged(start.select("*", F.array().cast("array<string>").alias("used"), F.array(at).alias("nodes")))
    levels = [front] if lo == 0 else []
    step = [*(F.col(a) for a in s), *(F.col(f"g{i}").alias(b) for i, b in enumerate(t))]
    for depth in range(1, (hi if hi is not None else TRAIL_ROUNDS) + 1):
        grown = front.join(hop, _equal(t, [f"f{i}" for i in range(keys)]) & ~F.array_contains("used", F.col("edge")))
        front = staged(grown.select(*step, F.lit(depth).cast("long").alias("hops"), F.array_append("used", F.col("edge")).alias("used"), F.array_append("nodes", to).alias("nodes")))
        if front.isEmpty():
            break
        if depth >= lo:
            levels.append(front)
        if hi is None and depth == TRAIL_ROUNDS:
            raise PathLimit(f"trails go on after {TRAIL_ROUNDS} hops; give an upper bound or ask for distinct ends")
    return _union(levels) if levels else front.where("false")


def frontier(link: DataFrame, seeds: DataFrame, keys: int = 1, lo: int = 1, hi: int | None = None, mode: str = "reach", ids: int = 1, until: DataFrame | None = None) -> DataFrame:
    """Level-synchronous expansion: ``reach`` or ``trails`` by ``mode``, as s0.., t0.., hops."""
    if mode == "reach":
        return reach(link, seeds, keys, lo, hi, ids, until=until)
    return trails(link, seeds, keys, lo, hi, ids).drop("used", "nodes")


def between(link: DataFrame, pairs: DataFrame, keys: int = 1, hi: int | None = None) -> DataFrame:
    """Least hops of each of the ``pairs`` (s0.., t0..), searched from both ends until they meet; unjoined ones are missing.

    After i rounds from the sources and j from the targets every path of at most i + j hops is known by a node on it.
    """
    s, t = _names(keys)
    x = [f"x{i}" for i in range(keys)]
    edges = staged(link.select(*s, *t))
    pairs = staged(pairs.select(*s, *t).distinct())
    sides = []
    for own, source, target in ((s, s, t), (t, t, s)):
        seeds = pairs.select(*(F.col(a).alias(b) for a, b in zip(own, s))).distinct()
        sides.append({"own": own, "hop": _hop(edges, source, target), "levels": [staged(_start(seeds, s, t))]})
    most, depth, ended = REACH_ROUNDS if hi is None else hi, 0, False
    while True:
        ahead, back = (_union(side["levels"]).select(*(F.col(a).alias(b) for a, b in zip(s, side["own"])), *(F.col(a).alias(b) for a, b in zip(t, x)), F.col("hops").alias(f"hops_{k}")) for k, side in enumerate(sides))
        met = staged(pairs.join(ahead, s).join(back, [*t, *x]).groupBy(*s, *t).agg(F.min(F.col("hops_0") + F.col("hops_1")).alias("hops")))
        done = met if hi is None else met.where(F.col("hops") <= hi)
        if ended or pairs.join(met, [*s, *t], "left_anti").isEmpty():
            return done
        if 2 * depth >= most:
            if hi is None:
                raise PathLimit(f"pairs are not joined after {most} hops; give an upper bound")
            return done
        depth += 2
        for side in sides:
            new: list[DataFrame] = []
            front = side["levels"][-1].where(F.col("hops") == depth - 2)
            for d in (depth - 1, depth):
                near = _one_on(new[-1] if new else front, side["hop"], s, t, d, False)
                new.append(near.join(_union(side["levels"] + new).select(*s, *t), [*s, *t], "left_anti").select(*s, *t, "hops"))
            found = staged(_union(new))
            side["levels"] = [*side["levels"], found] if len(side["levels"]) < 8 else [staged(_union(side["levels"])), found]
            ended = ended or found.where(F.col("hops") == depth).isEmpty()  # this side has seen all it can reach


def shortest_paths(link: DataFrame, seeds: DataFrame, keys: int = 1, lo: int = 1, hi: int | None = None, ids: int = 1, pairs: DataFrame | None = None, every: bool = True) -> DataFrame:
    """A row for every shortest path (or, without ``every``, one for each pair): s0.., t0.., hops, used, nodes.

    ``pairs`` (s0.., t0..) are those asked for, else all that the seeds reach. A node is joined to itself by the empty
    path only, and by none if ``lo`` is above 0. Paths are traced back along falling distances from the source.
    """
    s, t = _names(keys)
    x = [f"x{i}" for i in range(keys)]
    edges = staged(link)
    wanted = None if pairs is None else pairs.where(~_equal(s, t)) if lo else pairs
    near = staged(reach(edges, seeds, keys, 0, hi, ids, until=wanted))
    ends = near if pairs is None else near.join(pairs.select(*s, *t).distinct(), [*s, *t], "left_semi")
    ends = ends.where(F.col("hops") >= lo)

    def node(names: list[str]) -> Column:
        return F.col(names[0]) if keys == 1 else F.struct(*(F.col(b).alias(f"k{i}") for i, b in enumerate(names)))

    rows = staged(ends.select(*s, *t, "hops", *(F.col(b).alias(c) for b, c in zip(t, x)), F.col("hops").alias("left"), F.array(node(t)).alias("nodes"), F.array().cast("array<string>").alias("used")))
    hop = _hop(edges, s, t, ids).withColumnsRenamed({f"g{i}": c for i, c in enumerate(x)})
    before = near.select(*s, *(F.col(b).alias(f"f{i}") for i, b in enumerate(t)), F.col("hops").alias("least"))
    done = [rows.where("left = 0")]
    while not (open_rows := rows.where("left > 0")).isEmpty():
        grown = open_rows.join(hop, x).join(before, [*s, *(f"f{i}" for i in range(keys))]).where(F.col("least") == F.col("left") - 1)
        rows = staged(grown.select(*s, *t, "hops", *(F.col(f"f{i}").alias(c) for i, c in enumerate(x)), (F.col("left") - 1).alias("left"), F.array_prepend("nodes", node([f"f{i}" for i in range(keys)])).alias("nodes"), F.array_prepend("used", F.col("edge")).alias("used")))
        if not every:
            one = rows.groupBy(*s, *t, *x, "hops", "left").agg(F.min(F.struct("nodes", "used")).alias("p"))
            rows = staged(one.select(*s, *t, "hops", *x, "left", "p.nodes", "p.used"))
        done.append(rows.where("left = 0"))
    found = _union(done).select(*s, *t, "hops", "used", "nodes")
    return found if every else found.groupBy(*s, *t, "hops").agg(F.min(F.struct("nodes", "used")).alias("p")).select(*s, *t, "hops", "p.used", "p.nodes")


def ancestors(link: DataFrame, seeds: DataFrame, keys: int = 1, lo: int = 0, hi: int | None = None) -> DataFrame:
    """All ancestors of the seeds over a forest link: walked up to from few seeds, by doubling from many or far."""
    s, t = _names(keys)
    front = staged(_start(seeds, s, t))
    if front.count() > SMALL_ROWS // 10:
        return doubling(link, front.select(*s), keys, lo, hi)
    hop, levels, depth = _hop(link, s, t), [front], 0
    most = CLIMB_ROUNDS if hi is None else min(hi, CLIMB_ROUNDS)
    while depth < most:
        new: list[DataFrame] = []
        for _ in range(min(2 * SMALL_ROUNDS, most - depth)):
            depth += 1
            new.append(_one_on(new[-1] if new else front, hop, s, t, depth, False))
        levels.append(staged(_union(new)))
        front = levels[-1].where(F.col("hops") == depth)
        if front.isEmpty():
            return _union(levels).where(F.col("hops") >= lo)
    if hi is not None and hi <= depth:
        return _union(levels).where(F.col("hops") >= lo)
    return doubling(link, levels[0].select(*s), keys, lo, hi)


def doubling(link: DataFrame, seeds: DataFrame, keys: int = 1, lo: int = 0, hi: int | None = None) -> DataFrame:
    """All ancestors of the seeds over a link in which every source has one target and nothing runs in a circle.

    After k rounds ancestors nearer than 2**k are known and every node knows its ancestor 2**k steps up, so the
    number of joins is the logarithm of the depth.
    """
    s, t = _names(keys)
    jump = staged(link.select(*s, *t))
    found = staged(_start(seeds, s, t))
    near = 1
    while hi is None or near <= hi:
        up = jump.select(*(F.col(a).alias(f"f{i}") for i, a in enumerate(s)), *(F.col(b).alias(f"g{i}") for i, b in enumerate(t)))
        on = _equal(t, [f"f{i}" for i in range(keys)])
        more = staged(found.join(up, on).select(*s, *(F.col(f"g{i}").alias(b) for i, b in enumerate(t)), (F.col("hops") + near).alias("hops")))
        if more.isEmpty():
            dropped(more)
            break
        if near >= 1 << 30:
            raise PathLimit("the link is no forest: a path runs in a circle")
        found = replaced(found.unionByName(more), found, more)
        jump = replaced(jump.join(up, on).select(*s, *(F.col(f"g{i}").alias(b) for i, b in enumerate(t))), jump)
        near *= 2
    kept = found.where(F.col("hops") >= lo)
    return kept if hi is None else kept.where(F.col("hops") <= hi)


def exact(link: DataFrame, n: int, keys: int = 1, ids: int = 1, seeds: DataFrame | None = None) -> DataFrame:
    """A flat chain of ``n`` edge joins that repeats no edge: s0.., t0.., hops, used."""
    s, t = _names(keys)
    first = link.select(*s, *t, F.array(edge_text(ids)).alias("used"))
    rows = first if seeds is None else first.join(seeds.select(*s).distinct(), s)
    for _ in range(n - 1):
        rows = extended(rows, link, keys, ids)
    return rows.withColumn("hops", F.lit(n).cast("long"))


def extended(rows: DataFrame, link: DataFrame, keys: int = 1, ids: int = 1) -> DataFrame:
    """Chains one edge longer; an edge that a chain holds already is not taken again."""
    s, t = _names(keys)
    more = _hop(link, s, t, ids)
    joined = rows.join(more, _equal(t, [f"f{i}" for i in range(keys)]) & ~F.array_contains("used", F.col("edge")))
    return joined.select(*s, *(F.col(f"g{i}").alias(b) for i, b in enumerate(t)), F.array_append("used", F.col("edge")).alias("used"))


def ranged(link: DataFrame, lo: int, hi: int, form: str, keys: int = 1, ids: int = 1, seeds: DataFrame | None = None) -> DataFrame:
    """Trails of ``lo`` to ``hi`` hops in one of the forms unrolled, shared, frontier: s0.., t0.., hops."""
    s, t = _names(keys)
    if form == "frontier":
        start = seeds if seeds is not None else link.select(*s).distinct()
        return frontier(link, start, keys, lo, hi, "trail", ids)
    if form == "unrolled":
        parts = [exact(link, n, keys, ids, seeds).drop("used") for n in range(max(lo, 1), hi + 1)]
    elif form == "shared":
        rows, parts = staged(exact(link, 1, keys, ids, seeds).drop("hops")), []
        for n in range(1, hi + 1):
            if n > 1:
                rows = staged(extended(rows, link, keys, ids))
            if n >= lo:
                parts.append(rows.drop("used").withColumn("hops", F.lit(n).cast("long")))
    else:
        raise ValueError(f"no form {form!r}")
    if lo == 0:
        parts.append(_start(seeds if seeds is not None else link.select(*s), s, t))
    return reduce(DataFrame.unionByName, [p.select(*s, *t, "hops") for p in parts])


def shortest(link: DataFrame, source: DataFrame, target: DataFrame, weight: str | None = None, max_rounds: int | None = None, together: bool = False) -> DataFrame:
    """(s0, t0, cost, paths): least number of hops (or sum of ``weight``) and, by hops, how many shortest paths.

    Many sources advance together, a level a round. With weights, labels are corrected until none falls further;
    weights must not be negative. ``together`` takes the sources for one (s0 is null): a label for each node in place
    of one for each pair. Pairs that no path joins are missing. PathLimit if anything still moves after ``max_rounds``
    (REACH_ROUNDS if not given).
    """
    most = REACH_ROUNDS if max_rounds is None else max_rounds
    limit = PathLimit(f"distances still change after {most} rounds")
    edges = staged(link.select("s0", "t0", *([weight] if weight else [])))
    goal = target.select("t0").distinct()
    if weight is None:
        level = staged(source.select("s0").distinct().select("s0", F.col("s0").alias("t0"), F.lit(0).cast("double").alias("cost"), F.lit(1).cast("long").alias("paths")))
        done, before = level, level
        for depth in range(1, most + 2):
            near = level.join(edges.select(F.col("s0").alias("t0"), F.col("t0").alias("next")), "t0").groupBy("s0", F.col("next").alias("t0")).agg(F.sum("paths").alias("paths"))
            level = staged(near.join(done.select("s0", "t0"), ["s0", "t0"], "left_anti").select("s0", "t0", F.lit(float(depth)).alias("cost"), "paths"))
            if level.isEmpty():
                break
            if depth > most:
                raise limit
            done = replaced(done.unionByName(level), done, before)  # both tables of the round before
            before = level
        dropped(level)
        return done.join(goal, "t0").select("s0", "t0", "cost", "paths")
    own = F.lit(0).cast(source.schema["s0"].dataType) if together else F.col("s0")
    best = staged(source.select("s0").distinct().select(own.alias("s0"), F.col("s0").alias("t0"), F.lit(0.0).alias("cost"), F.lit(True).alias("moved")))
    hop = edges.select(F.col("s0").alias("t0"), F.col("t0").alias("next"), F.col(weight).cast("double").alias("w"))
    for depth in range(1, most + 2):
        reached = best.where("moved").join(hop, "t0").select("s0", F.col("next").alias("t0"), (F.col("cost") + F.col("w")).alias("cost"), F.lit(None).cast("double").alias("was"))
        both = best.select("s0", "t0", "cost", F.col("cost").alias("was")).unionByName(reached)
        best = replaced(both.groupBy("s0", "t0").agg(F.min("cost").alias("cost"), F.min("was").alias("was")).select("s0", "t0", "cost", (F.col("was").isNull() | (F.col("cost") < F.col("was"))).alias("moved")), best)
        if best.where("moved").isEmpty():
            break
        if depth > most:
            raise limit
    found = best.join(goal, "t0").select("s0", "t0", "cost", F.lit(1).cast("long").alias("paths"))
    return found.withColumn("s0", F.lit(None).cast(source.schema["s0"].dataType)) if together else found


def adjacency(link: DataFrame, chunk: int = 65_536) -> DataFrame:
    """Compact adjacency for one query: s0, part, out (sorted array of (t0, e0)), hubs cut into parts."""
    sized = link.groupBy("s0").agg(F.count("*").alias("degree"))
    dealt = link.join(sized, "s0").withColumn("part", F.pmod(F.xxhash64("e0"), F.greatest(F.lit(1), F.ceil(F.col("degree") / chunk))).cast("int"))
    return dealt.groupBy("s0", "part").agg(F.sort_array(F.collect_list(F.struct("t0", "e0"))).alias("out"))


def multi_source(link: DataFrame, sources: DataFrame, max_hops: int | None = None) -> DataFrame:
    """Least hops from every source to all it reaches, over the compact adjacency; all sources advance together."""
    rows = staged(adjacency(link)).select("s0", F.explode("out").alias("x")).select("s0", "x.t0", "x.e0")
    return frontier(rows, sources, 1, 0, max_hops, "reach")
