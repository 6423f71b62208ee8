"""Tuple-at-a-time traversal over adjacency lists in one process, under a budget."""

from __future__ import annotations

from pyspark.sql import DataFrame


class OutOfBudget(MemoryError):
    """The traversal would hold or visit more than it may."""


def adjacency_lists(link: DataFrame, budget: int) -> dict[int, list[tuple[int, int]]]:
    """source -> [(target, edge)], on the driver; refuses links of more than ``budget`` edges."""
    rows = link.select("s0", "t0", "e0").limit(budget + 1).collect()
    if len(rows) > budget:
        raise OutOfBudget(f"more than {budget} edges")
    out: dict[int, list[tuple[int, int]]] = {}
    for s, t, e in rows:
        out.setdefault(s, []).append((t, e))
    return out


def pointer_walk(lists: dict[int, list[tuple[int, int]]], seeds: list[int], hops: int, budget: int = 10_000_000) -> int:
    """Number of edge-unique chains of ``hops`` edges from the seeds, one tuple a step."""
    count = steps = 0
    stack = [(s, ()) for s in seeds]
    while stack:
        at, used = stack.pop()
        for target, edge in lists.get(at, ()):
            steps += 1
            if steps > budget:
                raise OutOfBudget(f"more than {budget} steps")
            if edge in used:
                continue
            if len(used) + 1 == hops:
                count += 1
            else:
                stack.append((target, (*used, edge)))
    return count
