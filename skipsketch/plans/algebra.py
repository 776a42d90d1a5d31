"""Query plans over bag algebra.

Conditions and expressions are SQL texts over the child's columns, compiled by Catalyst.  ``run`` turns a plan
into a DataFrame of signed rows: every row has a multiplicity ``__m``, so that a table with its update log is
one scan without consolidation, and linear operators need no state at all.
"""

from __future__ import annotations

import json
import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass, fields
from typing import Any

M = "__m"


class UnsupportedForMaintenance(ValueError):
    """The plan is outside what can be maintained; run it in full, or recapture."""


@dataclass(frozen=True)
class Node:
    def children(self) -> list[Node]:
        return [v for v in (getattr(self, f.name) for f in fields(self)) if isinstance(v, Node)]

    def walk(self) -> Iterator[Node]:
        yield self
        for c in self.children():
            yield from c.walk()

    def scans(self) -> list[Scan]:
        return [x for x in self.walk() if isinstance(x, Scan)]

    def tables(self) -> list[str]:
        return list(dict.fromkeys(s.table for s in self.scans()))


@dataclass(frozen=True)
class Scan(Node):
    """A table; ``prefix`` renames its columns, so that one table can be read twice."""

    table: str
    columns: tuple[str, ...]
    prefix: str = ""


@dataclass(frozen=True)
class Filter(Node):
    child: Node
    condition: str


@dataclass(frozen=True)
class Project(Node):
    child: Node
    exprs: tuple[tuple[str, str], ...]  # name, expression


@dataclass(frozen=True)
class Join(Node):
    """Equi-join on pairs of columns; without pairs a product.  ``condition`` is over both sides."""

    left: Node
    right: Node
    on: tuple[tuple[str, str], ...] = ()
    condition: str | None = None


@dataclass(frozen=True)
class Aggregate(Node):
    child: Node
    keys: tuple[str, ...]
    aggs: tuple[tuple[str, str, str], ...]  # name, sum | count | avg | min | max, expression ("*" to count rows)


@dataclass(frozen=True)
class Distinct(Node):
    child: Node


@dataclass(frozen=True)
class TopK(Node):
    child: Node
    order: tuple[tuple[str, bool], ...]  # column, descending
    k: int


@dataclass(frozen=True)
class UnionAll(Node):
    left: Node
    right: Node


def semi_join(left: Node, right: Node, on: tuple[tuple[str, str], ...]) -> Join:
    """Rows of ``left`` with a partner: a join with the distinct keys of ``right``."""
    keys = tuple(r for _, r in on)
    return Join(left, Distinct(Project(right, tuple((k, k) for k in keys))), on)


_literal = re.compile(r"(?i)\b(date|timestamp(?:_ntz)?)\s*'[^']*'|'(?:[^']|'')*'|(?<![\w.])[-+]?\d+(?:\.\d+)?(?:[eE][-+]?\d+)?\b")


def to_json(node: Node) -> dict[str, Any]:
    out: dict[str, Any] = {"op": type(node).__name__}
    for f in fields(node):
        v = getattr(node, f.name)
        out[f.name] = to_json(v) if isinstance(v, Node) else v
    return out


def from_json(data: dict[str, Any]) -> Node:
    kind = {c.__name__: c for c in (Scan, Filter, Project, Join, Aggregate, Distinct, TopK, UnionAll)}[data["op"]]
    deep = lambda v: tuple(map(deep, v)) if isinstance(v, list) else v
    return kind(**{k: from_json(v) if isinstance(v, dict) else deep(v) for k, v in data.items() if k != "op"})


def template_key(node: Node) -> str:
    """The plan with the constants of its selections as placeholders: the key of the catalog."""

    def masked(n: Node) -> dict[str, Any]:
        out = to_json(n)
        for name in out:
            v = getattr(n, name, None)
            if isinstance(v, Node):
                out[name] = masked(v)
            elif name == "condition" and v is not None:
                out[name] = " ".join(_literal.sub("?", v).split())
            elif name == "k":
                out[name] = "?"
        return out

    return json.dumps(masked(node), sort_keys=True)


def conjuncts(condition: str) -> list[str]:
    """The parts of a conjunction, split at top-level ANDs outside BETWEEN; lower-case keywords are read too."""
    parts, depth, between, start = [], 0, False, 0
    for m in re.finditer(r"'(?:[^']|'')*'|[()]|\b(?:and|between|case|end)\b", condition, re.I):
        t = m.group().lower()
        if t in ("(", "case"):
            depth += 1
        elif t in (")", "end"):
            depth -= 1
        elif depth == 0 and t == "between":
            between = True
        elif depth == 0 and t == "and":
            if between:
                between = False
            else:
                parts.append(condition[start : m.start()].strip())
                start = m.end()
    return [p for p in [*parts, condition[start:].strip()] if p]


def transform(node: Node, change: Callable[[Node], Node | None]) -> Node:
    """The plan with every node for which ``change`` gives another one replaced, top-down."""
    new = change(node)
    if new is not None:
        return new
    values = {f.name: getattr(node, f.name) for f in fields(node)}
    return type(node)(**{k: transform(v, change) if isinstance(v, Node) else v for k, v in values.items()})


def stateful(node: Node) -> bool:
    return any(isinstance(x, (Aggregate, Distinct, TopK)) for x in node.walk())
