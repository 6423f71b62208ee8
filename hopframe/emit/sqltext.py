"""SQL text of a relational plan in one dialect."""

from __future__ import annotations

import re
from enum import Enum
from typing import Any, assert_never

from hopframe.emit.functions import BINARY, FUNCTIONS
from hopframe.emit.kinds import integral, textual
from hopframe.lang import ast as A
from hopframe.plan import rel as R


class Dialect(Enum):
    SPARK = 0
    DUCKDB = 1


class Writer:
    """Prints expressions and plans. ``views`` names the results of path iterations that were run beforehand."""

    def __init__(self, dialect: Dialect, views: dict[R.Iterate, str] | None = None):
        self.dialect, self.views = dialect, views or {}
        self.with_clauses: list[str] = []
        self.recursions = 0

    # --- expressions
    def name(self, text: str) -> str:
        return f"`{text}`" if self.dialect is Dialect.SPARK else '"' + text.replace('"', '""') + '"'

    def literal(self, value: Any) -> str:
        match value:
            case None:
                return "NULL"
            case bool():
                return "true" if value else "false"
            case int():
                return str(value) if abs(value) < 1 << 31 else f"CAST({value} AS BIGINT)"
            case float():
                return f"CAST({value!r} AS DOUBLE)"
            case str():
                if self.dialect is Dialect.SPARK:
                    value = value.replace("\\", "\\\\")
                    return "'" + value.replace("'", "\\'") + "'"
                return "'" + value.replace("'", "''") + "'"
            case list() | tuple():
                return self.call("array", [self.literal(v) for v in value])
        raise TypeError(f"no literal for {value!r}")

    def call(self, name: str, args: list[str]) -> str:
        template = FUNCTIONS[name]
        if not isinstance(template, str):
            template = template[self.dialect.value]
        return re.sub(r"\{(\*|\d)\}", lambda m: ", ".join(args) if m[1] == "*" else args[int(m[1])], template)

    def expr(self, e: Any) -> str:
        x = self.expr
        match e:
            case R.Col("", name):
                return self.name(name)
            case R.Col(alias, name):
                return f"{alias}.{self.name(name)}"
            case R.Field(base, name):
                return f"{x(base)}.{self.name(name)}"
            case R.Row(items):
                if self.dialect is Dialect.SPARK:
                    return "named_struct(" + ", ".join(f"'{k}', {x(v)}" for k, v in items) + ")"
                return "struct_pack(" + ", ".join(f"{self.name(k)} := {x(v)}" for k, v in items) + ")"
            case A.Lit("*"):
                return "*"
            case A.Lit(value):
                return self.literal(value)
            case A.ListOf(items):
                return self.call("array", [x(i) for i in items])
            case A.Case(None, whens, other):
                return "CASE " + " ".join(f"WHEN {x(w)} THEN {x(t)}" for w, t in whens) + f" ELSE {x(other)} END"
            case A.Case(base, whens, other):
                return f"CASE {x(base)} " + " ".join(f"WHEN {x(w)} THEN {x(t)}" for w, t in whens) + f" ELSE {x(other)} END"
            case A.Comprehension():
                return self.comprehension(e)
            case A.Reduce(acc, start, var, source, step):
                if self.dialect is Dialect.SPARK:
                    return f"aggregate({x(source)}, {x(start)}, ({acc}, {var}) -> {x(step)})"
                return f"list_reduce(list_prepend({x(start)}, {x(source)}), lambda {acc}, {var}: {x(step)})"
            case A.Var(name):
                return name  # of a lambda
            case A.Call("in", (item, A.ListOf(items))):
                return f"({x(item)} IN ({', '.join(x(i) for i in items)}))" if items else "false"
            case A.Call("in", (item, source)):
                return self.call("member", [x(item), x(source)])
            case A.Call("/", (a, b)):
                if integral(a) and integral(b):
                    return f"({x(a)} DIV nullif({x(b)}, 0))" if self.dialect is Dialect.SPARK else f"({x(a)} // nullif({x(b)}, 0))"
                return f"(CAST({x(a)} AS DOUBLE) / nullif(CAST({x(b)} AS DOUBLE), 0))"
            case A.Call("+", (a, b)):
                return f"({x(a)} + {x(b)})" if not textual(a) and not textual(b) else f"concat({x(a)}, {x(b)})" if self.dialect is Dialect.SPARK else f"({x(a)} || {x(b)})"
            case A.Call("index", (source, i)):
                place = f"CASE WHEN {x(i)} >= 0 THEN {x(i)} + 1 ELSE {x(i)} END" if not isinstance(i, A.Lit) else str(i.value + 1 if i.value >= 0 else i.value)
                return f"try_element_at({x(source)}, {place})" if self.dialect is Dialect.SPARK else f"list_extract({x(source)}, {place})"
            case A.Call("slice", (source, lo, hi)):
                s = x(source)
                size = f"size({s})" if self.dialect is Dialect.SPARK else f"len({s})"
                low, high = self.bound(lo, size, "0"), self.bound(hi, size, size)
                if self.dialect is Dialect.SPARK:
                    return f"slice({s}, greatest({low}, 0) + 1, greatest(least({high}, {size}) - greatest({low}, 0), 0))"
                return f"list_slice({s}, greatest({low}, 0) + 1, greatest({high}, 0))"
            case A.Call("range", args):
                lo, hi = x(args[0]), x(args[1])
                step = x(args[2]) if len(args) > 2 else "1"
                return f"sequence({lo}, {hi}, {step})" if self.dialect is Dialect.SPARK else f"range({lo}, {hi} + sign({step}), {step})"
            case A.Call("substring", args):
                rest = f", {x(args[2])}" if len(args) > 2 else ""
                return f"substring({x(args[0])}, {x(args[1])} + 1{rest})"
            case A.Call("size" | "length", (a,)):
                return self.call("charlength" if textual(a) else "listlength", [x(a)])
            case A.Call(name, (a, b)) if name in BINARY:
                return f"({x(a)} {BINARY[name]} {x(b)})"
            case A.Call(name, args, distinct):
                return self.call(name + "_distinct" if distinct else name, [x(a) for a in args])
        raise TypeError(f"no SQL for {e!r}")

    def bound(self, e: Any, size: str, missing: str) -> str:
        """One end of a slice from the list's start; negative ends count from its end."""
        if e is None or (isinstance(e, A.Lit) and e.value is None):
            return missing
        text = self.expr(e)
        if isinstance(e, A.Lit):
            return text if e.value >= 0 else f"({size} + {text})"
        return f"(CASE WHEN {text} < 0 THEN {size} + {text} ELSE {text} END)"

    def comprehension(self, e: A.Comprehension) -> str:
        x, var = self.expr, e.var
        source = x(e.source)
        spark = self.dialect is Dialect.SPARK
        lam = (lambda body: f"{var} -> {body}") if spark else (lambda body: f"lambda {var}: {body}")
        if e.kind == "list":
            kept = source if e.keep is None else f"{'filter' if spark else 'list_filter'}({source}, {lam(x(e.keep))})"
            return kept if e.out is None else f"{'transform' if spark else 'list_transform'}({kept}, {lam(x(e.out))})"
        hits = f"{'size(filter' if spark else 'len(list_filter'}({source}, {lam(x(e.keep))}))"
        whole = f"{'size' if spark else 'len'}({source})"
        return {"any": f"({hits} > 0)", "all": f"({hits} = {whole})", "none": f"({hits} = 0)", "single": f"({hits} = 1)"}[e.kind]

    # --- plans
    def rel(self, rel: R.Rel) -> str:
        match rel:
            case R.Table(name):
                return self.name(name)
            case R.Union(parts, every):
                return f" UNION{' ALL' if every else ''} ".join(f"({self.rel(p)})" if isinstance(p, R.Select) and (p.order or p.limit is not None) else self.rel(p) for p in parts)
            case R.Iterate():
                return self.iterate(rel)
            case R.Select():
                return self.select(rel)
            case _ as never:
                assert_never(never)

    def source(self, rel: R.Rel, alias: str) -> str:
        text = self.rel(rel)
        plain = isinstance(rel, R.Table) or (isinstance(rel, R.Iterate) and " " not in text)
        return f"{text} {alias}" if plain else f"({text}) {alias}"

    def select(self, s: R.Select) -> str:
        x = self.expr
        columns = ", ".join(f"{x(e)} AS {self.name(n)}" for e, n in s.columns) or "1 AS one"
        text = f"SELECT {'DISTINCT ' if s.distinct else ''}{columns}"
        if s.source is not None:
            text += f" FROM {self.source(s.source, s.alias)}"
        for j in s.joins:
            on = " AND ".join(x(c) for c in j.on)
            kind = {"inner": "INNER JOIN", "left": "LEFT JOIN", "cross": "CROSS JOIN"}[j.kind if on or j.kind == "left" else "cross"]
            text += f" {kind} {self.source(j.rel, j.alias)}" + (f" ON {on or 'true'}" if kind != "CROSS JOIN" else "")
        if s.where:
            text += " WHERE " + " AND ".join(x(c) for c in s.where)
        if s.group:
            text += " GROUP BY " + ", ".join(x(g) for g in s.group)
        if s.order:
            text += " ORDER BY " + ", ".join(f"{self.name(n)} {'DESC NULLS FIRST' if d else 'ASC NULLS LAST'}" for n, d in s.order)
        if s.limit is not None:
            text += f" LIMIT {x(s.limit)}"
        if s.offset is not None:
            text += f" OFFSET {x(s.offset)}"
        return text

    def iterate(self, it: R.Iterate) -> str:
        """A finished iteration by its view, else a recursive common table expression (depth-limited in Spark)."""
        if it in self.views:
            return self.name(self.views[it])
        self.recursions += 1
        me, n = f"walk{self.recursions}", it.keys
        s, t = [f"s{i}" for i in range(n)], [f"t{i}" for i in range(n)]
        link, seeds = f"{me}_link", f"{me}_seed"
        self.with_clauses += [f"{link} AS ({self.rel(it.link)})", f"{seeds} AS ({self.rel(it.seeds)})"]
        keys = ", ".join(s + t)
        on = " AND ".join(f"w.{b} = l.{a}" for a, b in zip(s, t))
        start = ", ".join([f"d.{a} AS {a}" for a in s] + [f"d.{a} AS {b}" for a, b in zip(s, t)])
        onward = ", ".join([f"w.{a}" for a in s] + [f"l.{b}" for b in t])
        limit = f" AND w.hops < {it.hi}" if it.hi is not None else ""
        # a walk that comes back over the edge it took is no path, so undirected links need the edges
        plain = self.dialect is Dialect.DUCKDB and it.mode in ("reach", "shortest") and not it.undirected and not it.traced
        if plain and it.hi is None and it.mode == "reach":
            # pairs alone: the recursion ends when no pair is new
            one = f"SELECT {start} FROM {seeds} d" if it.lo == 0 else f"SELECT {', '.join([f'd.{a} AS {a}' for a in s] + [f'l.{b} AS {b}' for b in t])} FROM {seeds} d JOIN {link} l ON {' AND '.join(f'd.{a} = l.{a}' for a in s)}"
            self.with_clauses.append(f"{me} AS ({one} UNION SELECT {onward} FROM {me} w JOIN {link} l ON {on})")
            return f"SELECT {keys}, {it.lo} AS hops FROM {me}"
        if plain and it.hi is not None:
            self.with_clauses.append(f"{me} AS (SELECT {start}, 0 AS hops FROM {seeds} d UNION SELECT {onward}, w.hops + 1 FROM {me} w JOIN {link} l ON {on} WHERE true{limit})")
            return f"SELECT {keys}, min(hops) AS hops FROM {me} WHERE hops >= {it.lo} GROUP BY {keys}"
        duck = self.dialect is Dialect.DUCKDB
        ids = [f"l.e{i}" for i in range(it.ids)]
        edge = self.call("tostring", ids) if it.ids == 1 else self.call("edge text", [self.call("id text", [x]) for x in ids])
        node = "{0}.{1}0" if n == 1 else ("struct_pack(" if duck else "named_struct(") + ", ".join(f"k{i} := {{0}}.{{1}}{i}" if duck else f"'k{i}', {{0}}.{{1}}{i}" for i in range(n)) + ")"
        array, append = ("[{0}]", "list_append") if duck else ("array({0})", "array_append")
        used = f"{'list' if duck else 'array'}_contains(w.used, {edge})"
        first = f"SELECT {start}, 0 AS hops, CAST({'[] AS VARCHAR[]' if duck else 'array() AS ARRAY<STRING>'}) AS used, {array.format(node.format('d', 's'))} AS nodes FROM {seeds} d"
        step = f"SELECT {onward}, w.hops + 1, {append}(w.used, {edge}), {append}(w.nodes, {node.format('l', 't')}) FROM {me} w JOIN {link} l ON {on} WHERE NOT {used}{limit}"
        self.with_clauses.append(f"{me} AS ({first} UNION ALL {step})")
        if it.mode == "reach" or (it.mode == "shortest" and not it.traced):
            return f"SELECT {keys}, min(hops) AS hops FROM {me} WHERE hops >= {it.lo} GROUP BY {keys}"
        if it.mode in ("shortest", "all shortest"):
            every = f"SELECT *, rank() OVER (PARTITION BY {keys} ORDER BY hops) AS place, row_number() OVER (PARTITION BY {keys} ORDER BY hops, nodes, used) AS single FROM {me} WHERE hops >= {it.lo}"
            return f"SELECT {keys}, hops, used, nodes FROM ({every}) ranked WHERE {'place' if it.mode == 'all shortest' else 'single'} = 1"
        return f"SELECT {keys}, hops, used, nodes FROM {me} WHERE hops >= {it.lo}"

    def statement(self, rel: R.Rel) -> str:
        body = self.rel(rel)
        return f"WITH RECURSIVE {', '.join(self.with_clauses)} {body}" if self.with_clauses else body


def to_sql(rel: R.Rel, dialect: Dialect, views: dict[R.Iterate, str] | None = None) -> str:
    return Writer(dialect, views).statement(rel)
