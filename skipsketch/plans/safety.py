"""Which attributes may carry a sketch, and when a sketch of one query serves another.

These rules are our own, conservative ones: an attribute is refused unless the answer over the fragments that
hold the provenance is proven to be the answer over the whole table.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from decimal import Decimal

from skipsketch.plans.algebra import Aggregate, Distinct, Filter, Join, Node, Project, Scan, TopK, UnionAll, conjuncts, template_key

_number = r"[-+]?\d+(?:\.\d+)?(?:[eE][-+]?\d+)?"
_simple = re.compile(rf"^\s*(?P<e>.+?)\s*(?P<op><=|>=|<>|!=|=|<|>)\s*(?P<c>{_number})\s*$", re.S)
_between = re.compile(rf"^\s*(?P<e>.+?)\s+between\s+(?P<lo>{_number})\s+and\s+(?P<hi>{_number})\s*$", re.I | re.S)
_logical = re.compile(r"(?i)[<>=!]|\b(?:or|and|not|between|in|like|rlike|is|case)\b")
INF = Decimal("Infinity")


@dataclass(frozen=True)
class Interval:
    """Bounds are decimals as written, so that sums of decimals are compared with them exactly."""

    lo: Decimal = -INF
    hi: Decimal = INF
    lo_open: bool = False
    hi_open: bool = False

    def meet(self, o: Interval) -> Interval:
        lo, lo_open = max((self.lo, self.lo_open), (o.lo, o.lo_open))
        hi, hi_closed = min((self.hi, not self.hi_open), (o.hi, not o.hi_open))
        return Interval(lo, hi, lo_open, not hi_closed)

    def inside(self, o: Interval) -> bool:
        return (self.lo, self.lo_open) >= (o.lo, o.lo_open) and (self.hi, not self.hi_open) <= (o.hi, not o.hi_open)


def intervals(condition: str) -> tuple[dict[str, Interval], set[str]]:
    """Interval of each expression that is compared with a number; the other conjuncts as they stand."""
    out: dict[str, Interval] = {}
    rest = set()
    for part in conjuncts(condition):
        i = None
        if m := _between.match(part):
            i = Interval(Decimal(m["lo"]), Decimal(m["hi"]))
        elif (m := _simple.match(part)) and m["op"] not in ("<>", "!="):
            c = Decimal(m["c"])
            i = {"=": Interval(c, c), "<": Interval(hi=c, hi_open=True), "<=": Interval(hi=c), ">": Interval(c, lo_open=True), ">=": Interval(c)}[m["op"]]
        if i is None or _logical.search(m["e"]):  # a comparison inside a larger condition says nothing by itself
            rest.add(" ".join(part.split()))
            continue
        e = m["e"].strip()
        out[e] = out.get(e, Interval()).meet(i)
    return out, rest


def implies(narrow: str, wide: str) -> bool:
    """Whether the first condition entails the second, as far as intervals show."""
    a, rest_a = intervals(narrow)
    b, rest_b = intervals(wide)
    return rest_b <= rest_a and all(e in a and a[e].inside(i) for e, i in b.items())


def _columns(scan: Scan) -> list[str]:
    return [scan.prefix + c for c in scan.columns]


def paths(root: Node) -> list[list[Node]]:
    """The nodes from the root down to each table access, one list for each access."""
    if isinstance(root, Scan):
        return [[root]]
    return [[root, *p] for c in root.children() for p in paths(c)]


def carried(path: list[Node], column: str) -> list[set[str]]:
    """For each node of a path its output columns that hold the accessed table's column of every row unchanged.

    Projections rename or lose it, equi-joins add the column that equals it, groupings keep it as a key only.
    """
    names = {path[-1].prefix + column}
    out = [names]
    for node, child in zip(reversed(path[:-1]), reversed(path)):
        if isinstance(node, Project):
            names = {n for n, e in node.exprs if e.strip().strip("`") in names}
        elif isinstance(node, Join):
            mine = 0 if node.left is child else 1
            names = names | {pair[1 - mine] for pair in node.on if pair[mine] in names}
        elif isinstance(node, Aggregate):
            names = names & set(node.keys)
        out.append(names)
    return out[::-1]


def _own_columns(node: Node) -> set[str]:
    """Output columns that are columns of a table under their own name."""
    if isinstance(node, Scan):
        return set(_columns(node))
    if isinstance(node, Project):
        inner = _own_columns(node.child)
        return {n for n, e in node.exprs if e.strip() == n and n in inner}
    if isinstance(node, Join):
        return _own_columns(node.left) | _own_columns(node.right)
    if isinstance(node, UnionAll):
        return _own_columns(node.left) & _own_columns(node.right)
    if isinstance(node, Aggregate):
        return _own_columns(node.child) & set(node.keys)
    return _own_columns(node.children()[0])


def _never_negative(expr: str, agg: Aggregate, positive: set[str]) -> bool:
    """Whether it is known of this expression, and its names still mean the tables' columns."""
    return expr in positive and set(re.findall(r"[A-Za-z_]\w*", expr)) & set(_output(agg.child)) <= _own_columns(agg.child)


def _monotone(having: str, agg: Aggregate, positive: set[str]) -> bool:
    """Whether leaving out rows of a group can only make it fail: the condition is a lower bound of growing values."""
    kinds = {n: (f, e) for n, f, e in agg.aggs}
    found, rest = intervals(having)
    if rest:
        return False
    for e, i in found.items():
        if e in agg.keys:
            continue
        if e not in kinds:
            return False
        f, arg = kinds[e]
        grows = f in ("count", "max") or f == "sum" and _never_negative(arg, agg, positive)
        if not (grows and i.hi == INF or f == "min" and i.lo == -INF):
            return False
    return True


def is_safe(plan: Node, table: str, attr: str, positive: set[str] = frozenset(), determined: dict[str, set[str]] | None = None) -> bool:
    """Whether a sketch on table.attr keeps the answer.

    ``positive``: expressions known to be never negative.  ``determined``: for an attribute the sets of group
    keys that determine it, such as the order's date by the order's key.
    """
    return all(_safe_path(p, attr, positive, determined or {}) for p in paths(plan) if p[-1].table == table)


def _safe_path(path: list[Node], attr: str, positive: set[str], determined: dict[str, set[str]]) -> bool:
    tops = [i for i, n in enumerate(path) if isinstance(n, TopK)]
    if tops:
        # what drops rows of a top-k leaves their fragments out of the sketch, and others would move up
        if len(tops) > 1 or not all(isinstance(n, (Project, Aggregate, Distinct)) for n in path[: tops[0]]):
            return False
        path = path[tops[0] :]
    groups = [i for i, n in enumerate(path) if isinstance(n, (Aggregate, Distinct))]
    if any(isinstance(n, UnionAll) for n in path) and (groups or tops):
        return False
    if all(isinstance(path[i], Distinct) for i in groups):
        return True  # rules 1 and 4: rows left out cannot create results, nor move others up
    tracked = [carried(path, c) for c in {attr, *determined.get(attr, set())}]

    def by_keys(i: int) -> bool:
        g = path[i]
        keys = set(g.keys) if isinstance(g, Aggregate) else set(_output(g.child))
        return any(names[i + 1] & keys for names in tracked)

    if all(map(by_keys, groups)):
        return True  # rule 2: a group lies wholly in or out
    if len(groups) > 1:
        return False
    agg, above = path[groups[0]], path[: groups[0]]
    if any(isinstance(n, (Join, Project)) for n in above):
        return False
    having = [n for n in above if isinstance(n, Filter)]
    monotone = all(_monotone(h.condition, agg, positive) for h in having)
    if not tops:
        return monotone and bool(having)  # rule 3
    order = path[0].order
    if all(c in agg.keys for c, _ in order):
        return not having and set(c for c, _ in order) == set(agg.keys)  # rule 4: a partial group keeps its rank
    kinds = {n: (f, e) for n, f, e in agg.aggs}
    c, down = order[0]
    falling = down and c in kinds and (kinds[c][0] in ("count", "max") or kinds[c][0] == "sum" and _never_negative(kinds[c][1], agg, positive))
    return monotone and falling and len(order) == 1


def _output(node: Node) -> list[str]:
    if isinstance(node, Scan):
        return _columns(node)
    if isinstance(node, Project):
        return [n for n, _ in node.exprs]
    if isinstance(node, Aggregate):
        return [*node.keys, *(n for n, _, _ in node.aggs)]
    if isinstance(node, Join):
        return _output(node.left) + _output(node.right)
    return _output(node.children()[0])


def output_columns(node: Node) -> list[str]:
    return _output(node)


def choose_attribute(plan: Node, table: str, candidates: list[str], positive: set[str] = frozenset(), clustered: str | None = None) -> str | None:
    """A safe attribute; group-by attributes first, then the one that the files are sorted by."""
    safe = [c for c in candidates if is_safe(plan, table, c, positive)]
    grouped = [c for c in safe if is_group_key(plan, table, c)]
    return next(iter([*grouped, *(c for c in safe if c == clustered), *safe]), None)


def is_group_key(plan: Node, table: str, attr: str) -> bool:
    """Whether the attribute reaches a grouping as a key, under whatever name."""
    for path in paths(plan):
        if path[-1].table == table:
            names = carried(path, attr)
            if any(isinstance(n, Aggregate) and names[i + 1] & set(n.keys) for i, n in enumerate(path)):
                return True
    return False


def can_reuse(stored: Node, query: Node) -> bool:
    """Whether the sketch of ``stored`` covers the provenance of ``query``."""
    return template_key(stored) == template_key(query) and _covers(stored, query, False)


def _covers(a: Node, b: Node, beneath: bool) -> bool:
    """``beneath`` an aggregation or top-k a condition must be the same, above it may be narrower."""
    if isinstance(a, Filter):
        ok = " ".join(a.condition.split()) == " ".join(b.condition.split()) if beneath else implies(b.condition, a.condition)
        return ok and _covers(a.child, b.child, beneath)
    if isinstance(a, TopK):
        return b.k <= a.k and _covers(a.child, b.child, True)
    if isinstance(a, Join) and a.condition != b.condition and (beneath or not implies(b.condition or "", a.condition or "")):
        return False
    deeper = beneath or isinstance(a, (Aggregate, Distinct))
    return all(_covers(x, y, deeper) for x, y in zip(a.children(), b.children()))


def pushable_predicates(plan: Node, table: str) -> list[str]:
    """Conjuncts that may be applied when the delta of ``table`` is fetched: nothing stateful stands beneath them."""
    out: list[str] = []
    if sum(s.table == table for s in plan.scans()) > 1:
        return out  # one log serves both accesses

    def visit(n: Node) -> None:
        if isinstance(n, Filter) and not any(isinstance(x, (Aggregate, Distinct, TopK, Project, UnionAll)) for x in n.child.walk()):
            scans = n.child.scans()
            mine = [s for s in scans if s.table == table]
            if len(mine) == 1:
                own = set(_columns(mine[0]))
                other = {c for s in scans if s is not mine[0] for c in _columns(s)}
                for part in conjuncts(n.condition):
                    words = set(re.findall(r"[A-Za-z_]\w*", re.sub(r"'(?:[^']|'')*'", "", part)))
                    if words & own and not words & other and not mine[0].prefix:
                        out.append(part)
        for c in n.children():
            visit(c)

    visit(plan)
    return out
