"""All queries of the library but those for training data, with their SQL."""

from __future__ import annotations

from hopframe.functions import udfs
from hopframe.operators import queries as operators
from hopframe.sources import files, graphmap
from hopframe.streaming import live
from hopframe.workloads import extra, patterns, snb
from hopframe.workloads.base import Runner

WORKLOADS = patterns.PATTERNS | snb.ALL
QUERIES: dict[str, Runner] = {**WORKLOADS, **{k: run for k, (run, _) in extra.EXTRA.items()}}
ORACLES: dict[str, str] = {**{k: w.oracle for k, w in WORKLOADS.items()}, **{k: sql for k, (_, sql) in extra.EXTRA.items() if sql}}
for _module in (operators, files, graphmap, udfs, live):
    QUERIES |= _module.QUERIES
    ORACLES |= _module.ORACLES

#: the 41 benchmark queries
SUITE_41: dict[str, Runner] = {k: QUERIES[k] for k in [f"is{i}" for i in range(1, 8)] + [f"ic{i}" for i in range(1, 15)] + [f"bi{i}" for i in range(1, 21)]}
