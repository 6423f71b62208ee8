"""How workload queries are written down."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from typing import Any

from pyspark.sql import DataFrame, SparkSession

from hopframe.exec.session import GraphSession


@dataclass(frozen=True)
class Workload:
    """A graph query and hand-written SQL with the same rows."""

    text: str
    oracle: str
    params: dict[str, Any] = field(default_factory=dict)

    def __call__(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        return GraphSession(spark, source=sf_dir).cypher(self.text, **self.params)


Runner = Callable[[SparkSession, str], DataFrame]

#: events as edges, for the SQL side
TOUCH = "touch AS (SELECT event_id AS id, user_id AS src, CAST(json_extract_string(props, '$.k') AS BIGINT) AS dst, event_type AS ty, value AS v, ts FROM events)"
HOT = f"{TOUCH}, hot AS (SELECT * FROM touch WHERE ty = 'click' AND v > 80)"
#: both directions, loops once
BOTH = f"{TOUCH}, both_ways AS (SELECT id, src, dst, ts, v FROM touch UNION ALL SELECT id, dst, src, ts, v FROM touch WHERE src <> dst)"
HOT_BOTH = f"{HOT}, hu AS (SELECT id, src, dst, v FROM hot UNION ALL SELECT id, dst, src, v FROM hot WHERE src <> dst)"
#: neighbours over all interactions, each pair once
NB = f"{BOTH}, nb AS (SELECT DISTINCT src, dst FROM both_ways)"
#: ends of one and two hops over interactions of any type, both ways, from customer 7
NEAR2 = f"{NB}, near2 AS (SELECT id FROM (SELECT dst AS id FROM nb WHERE src = 7 UNION SELECT y.dst FROM nb x JOIN nb y ON x.dst = y.src WHERE x.src = 7) WHERE id <> 7)"
