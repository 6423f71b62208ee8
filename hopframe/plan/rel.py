"""Dialect-neutral relational plan."""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any


@dataclass(frozen=True)
class Col:
    """Column ``name`` of the source ``alias``; an alias of '' stands for an output column."""

    alias: str
    name: str
    kind: str | None = field(default=None, compare=False)  # 'integer', 'text' or 'other', where it is known


@dataclass(frozen=True)
class Field:
    """A field of a struct value."""

    base: Any
    name: str


@dataclass(frozen=True)
class Row:
    """A struct value of named fields."""

    items: tuple


@dataclass(frozen=True)
class Table:
    name: str


@dataclass(frozen=True)
class Iterate:
    """Pairs (s*, t*, hops) joined by a path over ``link`` (s*, t*, e*), from the sources in ``seeds`` (s*)."""

    link: Any
    seeds: Any
    keys: int
    ids: int
    lo: int
    hi: int | None
    #: 'reach': each pair once with its least length; 'trail': each path that repeats no edge; 'forest': single parents;
    #: 'shortest': one shortest path of each pair; 'all shortest': every one
    mode: str
    undirected: bool = False
    pairs: Any = None  # the (s*, t*) asked for, where both ends are known
    traced: bool = False  # with the edges used and the nodes passed, in order


@dataclass(frozen=True)
class Join:
    kind: str  # 'inner', 'left', 'cross'
    rel: Any
    alias: str
    on: tuple = ()


@dataclass(frozen=True)
class Select:
    source: Any  # None: one row without columns
    alias: str = "c"
    joins: tuple = ()
    where: tuple = ()
    columns: tuple = ()  # of (expression, name)
    group: tuple | None = None  # expressions; None: no grouping
    distinct: bool = False
    order: tuple = ()  # of (output column, descending)
    offset: Any = None
    limit: Any = None


@dataclass(frozen=True)
class Union:
    parts: tuple
    all: bool = True


Rel = Table | Iterate | Select | Union


@dataclass
class Counter:
    """Fresh names for one query."""

    made: dict[str, int] = field(default_factory=dict)

    def fresh(self, stem: str) -> str:
        self.made[stem] = self.made.get(stem, 0) + 1
        return f"{stem}{self.made[stem]}"
