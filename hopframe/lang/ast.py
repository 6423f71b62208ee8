"""Syntax tree of the read-only query language."""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any


@dataclass(frozen=True)
class Lit:
    value: Any


@dataclass(frozen=True)
class Param:
    name: str


@dataclass(frozen=True)
class Var:
    name: str


@dataclass(frozen=True)
class Prop:
    base: Any
    name: str


@dataclass(frozen=True)
class Call:
    """A function, operator or aggregate by lower-case name."""

    name: str
    args: tuple
    distinct: bool = False


@dataclass(frozen=True)
class Case:
    base: Any
    whens: tuple
    other: Any


@dataclass(frozen=True)
class ListOf:
    items: tuple


@dataclass(frozen=True)
class MapOf:
    items: tuple  # of (key, expression)


@dataclass(frozen=True)
class MapProjection:
    base: Any
    items: tuple  # of (key, expression or None)


@dataclass(frozen=True)
class Comprehension:
    """[var IN source WHERE keep | out]; also any/all/none/single by ``kind``."""

    kind: str
    var: str
    source: Any
    keep: Any
    out: Any


@dataclass(frozen=True)
class Reduce:
    acc: str
    start: Any
    var: str
    source: Any
    step: Any


@dataclass(frozen=True)
class HasLabel:
    base: Any
    labels: tuple


@dataclass(frozen=True)
class Block:
    """EXISTS, COUNT or COLLECT over a pattern block."""

    kind: str
    matches: tuple
    out: Any = None


@dataclass(frozen=True)
class NodePat:
    var: str | None
    labels: tuple = ()
    props: Any = None
    where: Any = None


@dataclass(frozen=True)
class RelPat:
    var: str | None
    types: tuple
    direction: str  # 'out', 'in', 'both'
    lo: int | None = None
    hi: int | None = None
    var_length: bool = False
    props: Any = None
    where: Any = None


@dataclass(frozen=True)
class PathPat:
    nodes: tuple
    rels: tuple
    var: str | None = None
    shortest: str | None = None  # 'one' or 'all'


@dataclass(frozen=True)
class Match:
    paths: tuple
    where: Any = None
    optional: bool = False


@dataclass(frozen=True)
class Projection:
    items: tuple  # of (expression, name); a name of None stands for *
    distinct: bool = False
    order: tuple = ()  # of (expression, descending)
    skip: Any = None
    limit: Any = None
    where: Any = None
    final: bool = False
    star: bool = False


@dataclass(frozen=True)
class Unwind:
    source: Any
    var: str


@dataclass(frozen=True)
class SubCall:
    query: Any
    imports: tuple


@dataclass(frozen=True)
class ProcCall:
    name: str
    args: tuple
    yields: tuple  # of (column, name)


@dataclass(frozen=True)
class Single:
    clauses: tuple


@dataclass(frozen=True)
class Query:
    parts: tuple  # of Single
    all: bool = True
    explain: str | None = field(default=None)
