"""Typed mapping catalog, read from YAML or a dict."""

from __future__ import annotations

from dataclasses import asdict, dataclass, field, replace
from enum import Enum
from pathlib import Path
from typing import Any

import yaml


class NodeAccess(Enum):
    """How a node's properties are reached."""

    OWN = "own"  # a table of its own
    INLINED = "inlined"  # columns of a link table
    IMPLIED = "implied"  # only an endpoint value


class EdgeAccess(Enum):
    """Where a relationship is stored."""

    SEPARATE = "separate"  # a link table
    TYPED = "typed"  # one value of a discriminator column
    KEY = "key"  # a key column of a node table


@dataclass(frozen=True)
class NodeMap:
    label: str
    access: NodeAccess
    key: tuple[str, ...]  # names of the key's parts; columns, for a table of its own
    table: str | None = None
    props: dict[str, str] = field(default_factory=dict)
    via: tuple[tuple[str, str], ...] = ()  # (edge, 'from' or 'to') that inline or imply it
    where: str | None = None


@dataclass(frozen=True)
class End:
    label: str
    cols: tuple[str, ...]  # expressions over the edge's row
    props: dict[str, str] = field(default_factory=dict)
    where: str | None = None  # discriminator of the endpoint's label


@dataclass(frozen=True)
class EdgeMap:
    type: str
    access: EdgeAccess
    source: End
    target: End
    table: str | None = None
    owner: str | None = None  # label whose table holds the key
    where: str | None = None
    type_column: str | None = None
    type_value: Any = None
    edge_key: tuple[str, ...] = ("*",)
    props: dict[str, str] = field(default_factory=dict)
    same_row_as: str | None = None
    single_parent: bool = False
    acyclic: bool = False
    included: bool = True  # endpoint keys all exist in the node tables
    name: str = ""  # of this entry; several entries may share a type


@dataclass(frozen=True)
class GraphMap:
    name: str
    nodes: dict[str, NodeMap]
    edges: dict[str, EdgeMap]

    @staticmethod
    def load(path: str | Path) -> GraphMap:
        return GraphMap.from_dict(yaml.safe_load(Path(path).read_text()))

    @staticmethod
    def commerce() -> GraphMap:
        """The given tables as a property graph."""
        return GraphMap.load(Path(__file__).parent.parent / "maps" / "commerce.yaml")

    @staticmethod
    def from_dict(raw: dict) -> GraphMap:
        nodes = {}
        for label, n in raw.get("nodes", {}).items():
            via = tuple((v["edge"], v["end"]) for v in n.get("via", []))
            nodes[label] = NodeMap(label, NodeAccess(n["access"]), tuple(n["key"]), n.get("table"), dict(n.get("props", {})), via, n.get("where"))
        entries: dict[str, dict] = raw.get("edges", {})

        def resolved(name: str) -> dict:
            e = entries[name]
            return resolved(e["extends"]) | {k: v for k, v in e.items() if k != "extends"} if "extends" in e else dict(e)

        edges: dict[str, EdgeMap] = {}
        for name in entries:
            e = resolved(name)
            kind = e.get("type", {}) if isinstance(e.get("type"), dict) else {}
            owner = e.get("owner")
            table = e.get("table") or (nodes[owner].table if owner else None)
            ends = e.get("endpoints")
            pairs = [(e["from"], t, f"{name}_{t['label']}") for t in ends] if ends else [(e["from"], e["to"], name)]
            for source, target, own in pairs:
                key = e.get("edge_key", nodes[owner].key if owner else "*")
                edges[own] = EdgeMap(
                    e.get("rel_type", name), EdgeAccess(e["access"]), _end(source), _end(target), table, owner, e.get("where"), kind.get("col"), kind.get("value"),
                    (key,) if isinstance(key, str) else tuple(key), dict(e.get("props", {})), e.get("same_row_as"), e.get("single_parent", False), e.get("acyclic", False), e.get("included", True), own,
                )
        out = GraphMap(raw.get("graph", "graph"), nodes, edges)
        out._closed()
        return out

    def _closed(self) -> None:
        for e in self.edges.values():
            for end in (e.source, e.target):
                if end.label not in self.nodes:
                    raise ValueError(f"edge {e.name} ends on the unknown label {end.label}")
                if len(end.cols) != len(self.nodes[end.label].key):
                    raise ValueError(f"edge {e.name}: {end.label} has a key of {len(self.nodes[end.label].key)} parts, {len(end.cols)} given")
            if e.same_row_as and e.same_row_as not in self.edges:
                raise ValueError(f"edge {e.name} shares rows with the unknown edge {e.same_row_as}")

    def to_yaml(self) -> str:
        def plain(x):
            if isinstance(x, Enum):
                return x.value
            if isinstance(x, dict):
                return {k: plain(v) for k, v in x.items() if v not in (None, {}, (), False)}
            return [plain(v) for v in x] if isinstance(x, tuple | list) else x

        nodes = {k: {a: b for a, b in plain(asdict(n)).items() if a not in ("label", "via")} | ({"via": [{"edge": e, "end": s} for e, s in n.via]} if n.via else {}) for k, n in self.nodes.items()}
        edges = {}
        for k, e in self.edges.items():
            d = plain(asdict(e))
            d = {a: b for a, b in d.items() if a not in ("name", "source", "target", "type", "type_column", "type_value")}
            d |= {"from": plain(asdict(e.source)), "to": plain(asdict(e.target)), "rel_type": e.type, "included": e.included}
            if e.type_column:
                d["type"] = {"col": e.type_column, "value": e.type_value}
            edges[k] = d
        return yaml.safe_dump({"graph": self.name, "nodes": nodes, "edges": edges}, sort_keys=False)

    def types(self) -> list[str]:
        return sorted({e.type for e in self.edges.values()})

    def edges_of(self, types: tuple[str, ...]) -> list[EdgeMap]:
        """Entries of these relationship types; all of them if none is named."""
        if unknown := set(types) - set(self.types()):
            raise ValueError(f"unknown relationship type {sorted(unknown)[0]}")
        return [e for e in self.edges.values() if not types or e.type in types]

    def with_edge(self, name: str, **changes) -> GraphMap:
        """The same map with one entry changed."""
        return replace(self, edges=self.edges | {name: replace(self.edges[name], **changes)})


def _end(raw: dict) -> End:
    return End(raw["label"], tuple(str(c) for c in raw["cols"]), dict(raw.get("props", {})), raw.get("where"))
