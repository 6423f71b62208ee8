"""The measures of the experiments."""

from __future__ import annotations

import re
import statistics
import time
from collections import Counter
from collections.abc import Callable
from dataclasses import dataclass
from decimal import Decimal

from pyspark.sql import DataFrame, SparkSession

from hopframe.workloads import snb


@dataclass(frozen=True)
class Timing:
    seconds: tuple[float, ...]

    @property
    def median_ms(self) -> float:
        return statistics.median(self.seconds) * 1000


def bench(run: Callable[[], DataFrame], runs: int = 5, cold: bool = False, spark: SparkSession | None = None) -> Timing:
    """``runs`` full executions; ``cold`` drops what the session has cached before each."""
    out = []
    for _ in range(runs):
        if cold and spark is not None:
            spark.catalog.clearCache()
        start = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        out.append(time.perf_counter() - start)
    return Timing(tuple(out))


def summary(timings: dict[str, Timing]) -> dict[str, dict[str, float]]:
    """Least, largest and median of the medians by query class (is, ic, bi and the other prefixes)."""
    by: dict[str, list[float]] = {}
    for name, t in timings.items():
        by.setdefault(re.match(r"[a-z]+", name)[0], []).append(t.median_ms)
    return {k: {"min": min(v), "max": max(v), "median": statistics.median(v)} for k, v in by.items()}


def scaling(small: dict[str, Timing], large: dict[str, Timing]) -> dict[str, float]:
    """Growth of each query's median, and the median of these under 'median'."""
    out = {k: large[k].median_ms / small[k].median_ms for k in small if k in large}
    return out | ({"median": statistics.median(out.values())} if out else {})


def ratio(slow: Timing, fast: Timing) -> float:
    """Speed-up, re-encoding tax, or cold over cached."""
    return slow.median_ms / fast.median_ms


CLASSES = {"procedure library": {"ic14", "bi15", "bi19", "bi20", "bi10"}, "call subquery": {"bi16", "bi4"}, "ambiguous endpoint": {"ic11", "bi17"}, "chained optional": {"is7"}, "endpoint across barrier": {"is2", "ic1", "ic3", "ic10", "bi12"}}


def coverage(spark: SparkSession, sf_dir: str, suite: dict[str, Callable] | None = None) -> list[dict]:
    """One row for each of the 41 benchmark queries: whether it ran here, whether it failed in the published run.

    The class by which each failing query is grouped is ours: the published run gives counts of classes only.
    """
    from hopframe.workloads.registry import SUITE_41

    out = []
    for name, run in (suite or SUITE_41).items():
        try:
            run(spark, sf_dir).write.format("noop").mode("overwrite").save()
            error = ""
        except Exception as e:  # noqa: BLE001  a failing query is a finding
            error = str(e).splitlines()[0][:200]
        out.append({"query": name, "ran": not error, "failed_there": name in snb.FAILED_THERE, "error": error})
    return out


def canonical(rows: list[tuple], digits: int = 6) -> Counter:
    """A multiset of rows in which equal results of two engines are equal."""

    def plain(x):
        if isinstance(x, bool) or x is None:
            return x
        if isinstance(x, float | Decimal):
            return round(float(x), digits) + 0.0
        if isinstance(x, int):
            return float(x)
        if isinstance(x, list | tuple):
            return tuple(plain(v) for v in x)
        return str(x)

    return Counter(tuple(plain(v) for v in r) for r in rows)


def parity(left: DataFrame | tuple[list[str], list[tuple]], right: DataFrame | tuple[list[str], list[tuple]]) -> bool:
    """Whether two results are the same multiset; columns are matched by name."""

    def sides(x):
        names, rows = (x.columns, [tuple(r) for r in x.collect()]) if isinstance(x, DataFrame) else x
        order = sorted(range(len(names)), key=lambda i: names[i])
        return [names[i] for i in order], canonical([tuple(r[i] for i in order) for r in rows])

    return sides(left) == sides(right)


def plan_shape(df: DataFrame) -> dict[str, int]:
    """Joins, exchanges, broadcasts and scans of the physical plan before adaptive changes."""
    text = df._jdf.queryExecution().sparkPlan().toString()
    full = df._jdf.queryExecution().executedPlan().toString()
    return {
        "joins": len(re.findall(r"(?:SortMergeJoin|BroadcastHashJoin|ShuffledHashJoin|BroadcastNestedLoopJoin|CartesianProduct)\b", text)),
        "exchanges": len(re.findall(r"\bExchange (?:hash|range|Single|Round)", full)),
        "broadcasts": len(re.findall(r"\bBroadcastExchange\b", full)),
        "scans": len(re.findall(r"\b(?:FileScan|BatchScan|Scan ExistingRDD)", text)),
    }
