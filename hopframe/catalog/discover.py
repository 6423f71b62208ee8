"""Proposes a map by probing tables; a person reviews the proposal."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: string columns of at most so many values are candidates for discriminators
FEW_VALUES = 12


@dataclass
class DraftMap:
    keys: dict[str, list[str]] = field(default_factory=dict)
    links: list[tuple[str, str, str, str, float]] = field(default_factory=list)  # table, column, table, key, score
    discriminators: list[tuple[str, str, int]] = field(default_factory=list)

    def to_dict(self) -> dict:
        """A map in the catalog's format, for review."""
        label = {t: "".join(x.title() for x in t.split("_")) for t in self.keys}
        nodes = {label[t]: {"access": "own", "table": t, "key": [k[0]], "props": {}} for t, k in self.keys.items() if k}
        edges = {}
        for table, column, other, key, _ in self.links:
            if self.keys.get(table) and self.keys.get(other):
                edges[f"{column.upper()}_TO_{other.upper()}"] = {"access": "key", "owner": label[table], "from": {"label": label[table], "cols": [self.keys[table][0]]}, "to": {"label": label[other], "cols": [column]}}
        return {"graph": "draft", "nodes": nodes, "edges": edges}


def _likeness(a: str, b: str) -> float:
    """Share of letter pairs that two names have in common, prefixes like ``o_`` aside."""
    pairs = [{x[i : i + 2] for i in range(len(x) - 1)} for x in (n.split("_", 1)[-1].lower() for n in (a, b))]
    return 2 * len(pairs[0] & pairs[1]) / max(1, len(pairs[0]) + len(pairs[1]))


def column_profile(name: str, df: DataFrame) -> DataFrame:
    """(table, column, kind, rows, values) of all whole-number and string columns, in one pass."""
    chosen = [f for f in df.schema.fields if f.dataType.simpleString() in ("bigint", "int", "string")]
    counts = df.agg(F.count("*").alias("rows"), *(F.count_distinct(f.name).alias(f"v_{f.name}") for f in chosen))
    triples = F.array(*(F.struct(F.lit(f.name).alias("column"), F.lit(f.dataType.simpleString()).alias("kind"), F.col(f"v_{f.name}").alias("values")) for f in chosen))
    return counts.select(F.lit(name).alias("table"), "rows", F.explode(triples).alias("x")).select("table", "x.column", "x.kind", "rows", "x.values")


def propose(tables: dict[str, DataFrame], least_score: float = 0.3) -> DraftMap:
    """Keys are whole-number columns of distinct values; links are columns whose values are all among a key's.

    Inclusion is first tried on a sample. Names that resemble each other raise a link's score.
    """
    draft = DraftMap()
    profiles = {t: column_profile(t, df).collect() for t, df in tables.items()}  # a row for each column
    for t, rows in profiles.items():
        draft.keys[t] = [r["column"] for r in rows if r["kind"] != "string" and r["rows"] and r["values"] == r["rows"]]
        draft.discriminators += [(t, r["column"], r["values"]) for r in rows if r["kind"] == "string" and 1 < r["values"] <= FEW_VALUES]
    for t, rows in profiles.items():
        for r in rows:
            if r["kind"] == "string" or r["column"] in draft.keys[t]:
                continue
            for other, keys in draft.keys.items():
                for key in keys[:1]:
                    score = _likeness(r["column"], key)
                    if score < least_score:
                        continue
                    values, known = tables[t].select(F.col(r["column"]).alias("k")).where("k is not null"), tables[other].select(F.col(key).alias("k"))
                    if values.limit(1000).join(known, "k", "left_anti").isEmpty() and values.join(known, "k", "left_anti").isEmpty():
                        draft.links.append((t, r["column"], other, key, round(score, 3)))
    return draft
