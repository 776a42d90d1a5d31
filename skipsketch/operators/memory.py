"""Maintenance with the operator state in the driver's memory, for small deltas and bounded state.

Sums are whole numbers of 10 ** -PLACES, the decimals of the tables backend, and compared with decimal bounds, so
both backends decide alike.

What lies below the first aggregation runs as a DataFrame over the delta, or, for selections, projections and equi-joins
of rows that are still on the driver, without a job: the other side of a join is read once, counted before, and then
follows its own deltas.  The few result rows go through the aggregation, the conditions above it, the top-k and the
merge as Python objects.  The delta and the state are checked against bounds before they are gathered.  A longer delta
is folded to its groups by Spark and goes through the state group by group; a larger state moves to the tables backend,
unless it is ``strict``, which refuses both.  A side beyond its bound is left to Spark, which joins it with the delta.
"""

from __future__ import annotations

import bisect
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field, replace
from decimal import Decimal
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from skipsketch.functions.local import CTX, NotLocal, compiled, exact, scaled, unscaled
from skipsketch.functions.ranges import Partitioning, RangeSet
from skipsketch.operators.aggregate import PLACES, AggregateOp, argument
from skipsketch.operators.annotated import Annotated
from skipsketch.operators.maintain import Options, Sketch, capture, delta_of, full, maintain, merged
from skipsketch.operators.ranked import Ranked
from skipsketch.plans.algebra import Aggregate, Filter, Join, M, Node, Project, Scan, TopK, UnsupportedForMaintenance, stateful
from skipsketch.plans.safety import INF, Interval, intervals
from skipsketch.sources.delta import Database
from skipsketch.sources.shared import stored

#: Rows of a delta, after its joins, that are gathered as they are, and entries of the state (groups, fragments of groups
#: that their keys don't tell, values) up to which memory is used.  A group with one sum takes about 0.4 kB of the driver's
#: Python, 1.1 kB with its position in a top-k, and a driver has little beside Spark's heap: 900,000 of a
#: top-k didn't fit into 1500 MB with it.
MOST_DELTA, MOST_STATE = 50_000, 250_000
#: Rows of a join's side up to which a delta of the other side meets them in memory; beyond it they meet in Spark.
MOST_SIDE = 200_000


class TooLarge(UnsupportedForMaintenance):
    """Beyond a bound of the memory backend."""


@dataclass(slots=True)
class Group:
    cnt: int = 0
    sums: list = field(default_factory=list)
    nn: list = field(default_factory=list)
    frags: dict[int, int] | tuple = field(default_factory=dict)  # empty where the key tells the fragment
    values: list[dict] | tuple = field(default_factory=list)  # of each min or max: value -> rows
    sorted: list[list] | tuple = field(default_factory=list)

    def entries(self) -> int:
        return 1 + len(self.frags) + sum(map(len, self.values))


#: A row by column names, its fragments, its multiplicity.
Move = tuple[dict[str, Any], tuple, int]


class HeldSide:
    """The rows of one side of a join by its join columns, up to ``MOST_SIDE`` of them; without an index beyond that."""

    def __init__(self, columns: list[str], on: tuple[str, ...], version: int):
        self.columns, self.on, self.version = columns, on, version
        self.index: dict[tuple, dict[tuple, int]] | None = {}
        self.rows = 0

    @classmethod
    def of(cls, side: Annotated, on: tuple[str, ...], version: int) -> HeldSide:
        out = cls(side.columns, on, version)
        rows = side.df.select(*(F.col(f"`{c}`") for c in out.columns), F.array(*side.thin) if not side.wide else side.sketch(), M)
        if rows.limit(MOST_SIDE + 1).count() > MOST_SIDE:
            out.index = None
            return out
        for r in rows.toLocalIterator():
            out.add(tuple(r[:-2]), tuple(r[-2]), r[-1])
            if out.index is None:
                break
        return out

    def add(self, row: tuple, frags: tuple, m: int) -> None:
        key = tuple(row[self.columns.index(c)] for c in self.on)
        if None in key:  # has no partner
            return
        try:
            if any(isinstance(x, float) for x in key):  # Spark's equality of NaN isn't Python's
                raise TypeError
            found = self.index.setdefault(key, {})
            n = found.get((row, frags), 0) + m
            self.rows += ((row, frags) not in found) - (not n)
            if n:
                found[row, frags] = n
            else:
                found.pop((row, frags), None)
        except TypeError:  # arrays, maps and binary values can't be looked up
            self.index = None
        if self.rows > MOST_SIDE:
            self.index = None

    def moved(self, moves: list[Move], version: int) -> HeldSide:
        for now, frags, m in moves:
            if self.index is not None:
                self.add(tuple(now[c] for c in self.columns), frags, m)
        self.version = version
        return self

    def partners(self, key: tuple) -> Any:
        if any(isinstance(x, float) for x in key):
            raise NotLocal("a join of doubles")
        return () if None in key else self.index.get(key, {}).items()


def _ordered(v: Any) -> Any:
    if isinstance(v, float) and v != v:
        raise UnsupportedForMaintenance("in memory: NaN under a minimum or maximum")
    return v


def _mean(total: int, n: int) -> Decimal:
    """Rounded as Spark rounds a quotient of decimals."""
    return CTX.quantize(CTX.quantize(CTX.divide(unscaled(total), Decimal(n)), Decimal(1).scaleb(-PLACES - 1)), Decimal(1).scaleb(-PLACES))


def _bound(bound: Decimal, value: Any) -> Any:
    """A bound in the type of the value that it is compared with."""
    if isinstance(value, float):
        return float(bound)
    if isinstance(value, Decimal):
        return CTX.quantize(bound, Decimal(1).scaleb(-PLACES)) if bound.is_finite() else bound
    if not isinstance(value, int):
        raise UnsupportedForMaintenance("in memory: a number is compared with something else")
    return bound


class MemorySketch:
    """``strict``: what is too large for memory is refused; else it is done all the same, in the end on state tables."""

    def __init__(self, db: Database, plan: Node, phi: Partitioning, version: int | None = None, strict: bool = False):
        self.db, self.plan, self.phi, self.strict = db, plan, phi, strict
        self.tables: Sketch | None = None  # instead of all below, once the state is too large
        self.version = db.version if version is None else version
        node, self.top, self.having = plan, None, []
        if isinstance(node, TopK):
            self.top, node = node, node.child
        while isinstance(node, Filter):
            self.having.append(node.condition)
            node = node.child
        if not isinstance(node, Aggregate) or stateful(node.child):
            raise UnsupportedForMaintenance("in memory: one aggregation, conditions above it, and a top-k")
        self.node, self.base = node, node.child
        self.names = [*node.keys, *(n for n, _, _ in node.aggs)]
        self.bounds = self._bounds(self.having)
        self.linear = [i for i, (_, f, _) in enumerate(node.aggs) if f not in ("min", "max")]
        self.ordered = [i for i, (_, f, _) in enumerate(node.aggs) if f in ("min", "max")]
        self.groups: dict[tuple, Group] = {}
        self.counters: dict[int, int] = {}
        self.rows = Ranked()  # of a top-k: (order, row, sketch)
        self.sides: dict[tuple[Node, tuple[str, ...]], HeldSide] = {}  # of joins below the aggregation
        self.op, self.keyed, self.entries = AggregateOp(db.spark, node, phi), [], 0
        self.told: dict[tuple, tuple] = {}  # fragments as keys tell them, each tuple once
        try:
            self._capture()
        except TooLarge:
            self._to_tables(self.version)

    @property
    def fragments(self) -> set[int]:
        return set(self.counters)

    def by_table(self) -> dict[str, set[int]]:
        return self.phi.split(self.fragments)

    def _bounds(self, conditions: list[str]) -> list[tuple[int, Interval]]:
        out = []
        for condition in conditions:
            found, rest = intervals(condition)
            if rest or not set(found) <= set(self.names):
                raise UnsupportedForMaintenance(f"in memory: {condition}")
            out += [(self.names.index(e), i) for e, i in found.items()]
        return out

    def _above(self, plan: Node) -> list[tuple[int, Interval]] | None:
        """The bounds of another query's conditions on the same groups; None if it isn't on them."""
        conditions = []
        while isinstance(plan, Filter):
            conditions.append(plan.condition)
            plan = plan.child
        if plan != self.node:
            return None
        try:
            return self._bounds(conditions)
        except UnsupportedForMaintenance:
            return None

    def serves(self, plan: Node) -> bool:
        if self.tables is not None:
            return plan == self.plan
        return self._above(plan) is not None

    def fragments_for(self, plan: Node) -> set[int]:
        """The accurate sketch of another query that this state serves."""
        if self.tables is not None:
            return self.fragments
        bounds = self._above(plan)
        out: set[int] = set()
        for key, g in self.groups.items():
            if self._row(key, g, bounds) is not None:
                out.update(self._frags(key, g))
        return out

    # ---- from rows to state ------------------------------------------------------------------------------

    def _capture(self) -> None:
        below = full(self.db, self.base, self.phi, self.version)
        found, self.op.keyed = self.op.keyed, self._keyed(below)
        groups, frags, values = self.op.fold(below)
        if any(getattr(f.dataType, "scale", 0) > PLACES for f in groups.schema if f.name.startswith("sum_")):
            raise UnsupportedForMaintenance("in memory: decimals of more places")
        groups, frags = stored(groups, "memory"), None if frags is None else stored(frags, "memory")
        values = {n: stored(x, "memory") for n, x in values.items()}
        self.entries = sum(x.count() for x in (groups, frags, *values.values()) if x is not None)
        if self.entries > MOST_STATE:  # from the files' footers, before anything is gathered
            if found == self.op.keyed:
                self.op.folded = groups, frags, values  # for the tables, so that the rows are read and joined once
            raise TooLarge("in memory: too large a state")
        k = len(self.node.keys)
        for r in groups.toLocalIterator():
            g = self.groups[tuple(r[:k])] = self._new()
            g.cnt = r["cnt"]
            for j, i in enumerate(self.linear):
                n, f, e = self.node.aggs[i]
                g.nn[j] = r[f"nn_{n}"]
                g.sums[j] = scaled(r[f"sum_{n}"]) if f != "count" and e != "*" else 0
        for r in frags.toLocalIterator() if frags is not None else ():
            self.groups[tuple(r[:k])].frags[r["frag"]] = r["cnt"]
        for j, i in enumerate(self.ordered):
            for r in values[self.node.aggs[i][0]].toLocalIterator():
                g = self.groups[tuple(r[:k])]
                g.values[j][_ordered(r["v"])] = r["cnt"]
        rows = []
        for key, g in self.groups.items():
            if self.ordered:
                g.sorted = [sorted(v) for v in g.values]
            if (row := self._row(key, g)) is None:
                continue
            if self.top:
                rows.append(self._item(row, self._frags(key, g)))
            else:
                self._count(self._frags(key, g), 1, self.counters)
        if self.top:
            self._count_top([], rows, self.counters)

    def _keyed(self, below: Annotated) -> list[tuple[str, str]] | None:
        """The keys that tell a group's fragment on the driver too: whole numbers, within bounds that are."""
        whole = {f.name for f in below.df.schema if isinstance(f.dataType, T.IntegralType)}
        found = self.op.keyed
        if found is None or not all(c in whole and all(type(x) is int for x in self.phi.ranges[t].cuts) for t, c in found):
            found = None
        self.keyed = None if found is None else [(self.phi.offset[t], self.phi.ranges[t], self.node.keys.index(c)) for t, c in found]
        return found

    def _frags(self, key: tuple, g: Group) -> tuple:
        """The fragments that hold the group's rows."""
        if self.keyed is None:
            return tuple(g.frags)
        found = tuple(sorted({at + ranges.fragment_of(key[i]) for at, ranges, i in self.keyed}))
        return self.told.setdefault(found, found)

    def _to_tables(self, version: int) -> None:
        """Go on with state tables, which have no bound."""
        if self.strict:
            raise TooLarge("in memory: too large a state")
        self.groups, self.rows, self.sides, self.told, self.entries = {}, Ranked(), {}, {}, 0
        self.tables = capture(self.db, self.plan, self.phi, version, ops={self.node: self.op} if self.op.folded else None)
        self.version, self.counters = version, self.tables.counters

    def _new(self) -> Group:
        n = len(self.linear)
        return Group(0, [0] * n, [0] * n, {} if self.keyed is None else (), [{} for _ in self.ordered] or (), [[] for _ in self.ordered] or ())

    def _row(self, key: tuple, g: Group, bounds: list[tuple[int, Interval]] | None = None) -> tuple | None:
        """The group's result row, if it has one that meets the conditions."""
        if g.cnt <= 0:
            return None
        out: list = [None] * len(self.node.aggs)
        for j, i in enumerate(self.linear):
            f = self.node.aggs[i][1]
            out[i] = g.nn[j] if f == "count" else None if not g.nn[j] else unscaled(g.sums[j]) if f == "sum" else _mean(g.sums[j], g.nn[j])
        for j, i in enumerate(self.ordered):
            found = g.sorted[j]
            out[i] = None if not found else found[0] if self.node.aggs[i][1] == "min" else found[-1]
        row = (*key, *out)
        for at, i in self.bounds if bounds is None else bounds:
            x = row[at]
            if x is None:
                return None
            lo, hi = _bound(i.lo, x), _bound(i.hi, x)
            if not ((x > lo or (x == lo and not i.lo_open)) and (x < hi or (x == hi and not i.hi_open))):
                return None
        return row

    def _order(self, row: tuple) -> tuple:
        out = []
        for c, down in self.top.order:
            x = row[self.names.index(c)]
            if down and x is not None and not isinstance(x, (int, float, Decimal)):
                raise UnsupportedForMaintenance("in memory: a falling order of something else than numbers")
            out.append((x is None, INF if x is None else x if not down else CTX.minus(x) if isinstance(x, Decimal) else -x))
        return (*out, *((x is None, 0 if x is None else x) for x in row))

    def _item(self, row: tuple, frags: tuple) -> tuple:
        return self._order(row), row, frags if self.keyed is not None else tuple(sorted(frags))

    @staticmethod
    def _count(frags: tuple, sign: int, changes: dict[int, int]) -> None:
        for f in frags:
            changes[f] = changes.get(f, 0) + sign

    def _count_top(self, gone: list[tuple], new: list[tuple], changes: dict[int, int]) -> None:
        """Replace rows of a top-k's input; only positions that change among the first k are counted."""
        if not len(self.rows) and not gone:
            self.rows = Ranked(new)
            leaving, entering = [], [self.rows[i] for i in range(min(self.top.k, len(new)))]
        else:
            leaving, entering = self.rows.replaced(gone, new, self.top.k)
        for sign, items in ((-1, leaving), (1, entering)):
            for _, _, frags in items:
                self._count(frags, sign, changes)

    # ---- maintenance -------------------------------------------------------------------------------------

    def gather(self, delta: Annotated) -> list[tuple]:
        """key, arguments, fragments, multiplicity of each delta row."""
        args = [F.lit(1) if e == "*" else F.expr(e) if f in ("count", "min", "max") else argument(delta.df, e) for _, f, e in self.node.aggs]
        rows = delta.df.select(F.array(*delta.thin) if not delta.wide else delta.sketch(), M, *self.node.keys, *(a.alias(f"__a{i}") for i, a in enumerate(args)))
        if any(isinstance(n, Join) for n in self.base.walk()):  # a join may make more rows than the log has; one job either way
            rows = rows.limit(MOST_DELTA + 1).where(F.col(M) != 0)
        k, sums = len(self.node.keys), {i for i, (_, f, _) in enumerate(self.node.aggs) if f in ("sum", "avg")}
        found = rows.collect()
        if len(found) > MOST_DELTA:
            raise TooLarge("in memory: too large a delta")
        return [(tuple(r[2 : 2 + k]), tuple(scaled(x) if i in sums and x is not None else x for i, x in enumerate(r[2 + k :])), r[0], r[1]) for r in found]

    def maintain(self, version: int | None = None) -> dict[int, int]:
        """Bring the sketch to a version; returns its delta."""
        version = self.db.version if version is None else version
        if self.tables is not None:
            changes = maintain(self.db, self.tables, version)
            self.version, self.counters = version, self.tables.counters
            return changes
        try:
            delta = self._delta(version)
        except TooLarge:
            if self.strict:
                raise
            delta = None
        if delta is not None:
            changes = self.apply(delta)
        else:
            changes = self.advance(self._folded(self._changes(version)))
        if self.entries <= MOST_STATE:
            self.version = version
            return merged(self.counters, changes)
        before = self.fragments
        self._to_tables(version)
        return {f: 1 if f in self.fragments else -1 for f in before ^ self.fragments}

    def _changes(self, version: int) -> Annotated | None:
        return delta_of(self.db, Sketch(self.base, self.phi, self.version, {}, options=Options()), version)

    def _delta(self, version: int) -> list[tuple]:
        """The delta's rows, where they are few enough to be on the driver."""
        if sum(self.db[t].rows_between(self.version, version) for t in self.plan.tables()) > MOST_DELTA:
            raise TooLarge("in memory: too large a delta")
        held = self._local(version)
        if held is not None:
            return held
        found = self._changes(version)
        return self.gather(found) if found is not None else []

    def _folded(self, delta: Annotated | None) -> Iterator[tuple[tuple, Group]]:
        """What a delta of any length adds to each group; the parts of a group come one after the other."""
        if delta is None:
            return
        if self.keyed is None or self.ordered:  # folded more than once
            delta = replace(delta, df=stored(delta.df, "delta"))
        groups, frags, values = self.op.fold(delta)
        k, names = list(self.node.keys), [self.node.aggs[i][0] for i in self.ordered]
        others = [] if frags is None else [frags.withColumnRenamed("cnt", "__n")]
        others += [values[n].select(*k, F.col("v").alias(f"__v{j}"), F.col("cnt").alias("__n")) for j, n in enumerate(names)]
        rows = groups
        for x in others:
            rows = rows.unionByName(x, allowMissingColumns=True)
        if others:
            rows = rows.repartition(*k).sortWithinPartitions(*k) if k else rows.coalesce(1)
        yield from self._grouped(rows, len(k))

    def _grouped(self, rows: DataFrame, k: int) -> Iterator[tuple[tuple, Group]]:
        at = {c: i for i, c in enumerate(rows.columns)}
        linear = [(at[f"nn_{n}"], at[f"sum_{n}"] if f != "count" and e != "*" else None) for n, f, e in (self.node.aggs[i] for i in self.linear)]
        ordered = [at[f"__v{j}"] for j in range(len(self.ordered))]
        last, d = None, None
        for r in rows.toLocalIterator(prefetchPartitions=True):
            if d is None or last != r[:k]:
                if d is not None:
                    yield tuple(last), d
                last, d = r[:k], self._new()
            if r[at["cnt"]] is not None:
                d.cnt = r[at["cnt"]]
                for j, (n, x) in enumerate(linear):
                    d.nn[j] = r[n]
                    d.sums[j] = 0 if x is None else scaled(r[x])
            elif "frag" in at and r[at["frag"]] is not None:
                d.frags[r[at["frag"]]] = r[at["__n"]]
            else:
                for j, i in enumerate(ordered):
                    if r[i] is not None:
                        d.values[j][_ordered(r[i])] = r[at["__n"]]
        if d is not None:
            yield tuple(last), d

    def _local(self, version: int) -> list[tuple] | None:
        """The same from rows that are on the driver, without a job; None where Spark is needed."""
        try:
            out = []
            for now, frags, m in self._moves(self.base, self.version, version):
                args = tuple(1 if e == "*" else None if now.get(e, 0) is None else self._argument(f, now[e] if e in now else compiled(e)[0](now)) for _, f, e in self.node.aggs)
                out.append((tuple(now[k] for k in self.node.keys), args, frags, m))
        except NotLocal:
            return None
        return out

    def _moves(self, node: Node, since: int, version: int) -> list[Move]:
        """Signed rows of a node between two versions, from deltas and sides of joins that are on the driver."""
        if isinstance(node, Scan):
            table, ranges = self.db[node.table], self.phi.ranges.get(node.table)
            wanted = [v for v in table.log if since < v <= version]
            if not all(v in table.recent for v in wanted) or not (ranges is None or isinstance(ranges, RangeSet)):
                raise NotLocal("written deltas, or a grid")
            at = {c: i for i, c in enumerate(table.columns)}
            out = []
            for row in (r for v in wanted for r in table.recent[v]):
                frags = () if ranges is None else (self.phi.offset[node.table] + ranges.fragment_of(row[at[ranges.attr]]),)
                out.append(({node.prefix + c: row[at[c]] for c in node.columns}, frags, row[-1]))
            return out
        if isinstance(node, Filter):
            holds = compiled(node.condition)[0]
            return [r for r in self._moves(node.child, since, version) if holds(r[0])]
        if isinstance(node, Project):
            return [({n: now[e.strip()] if e.strip() in now else compiled(e)[0](now) for n, e in node.exprs}, frags, m) for now, frags, m in self._moves(node.child, since, version)]
        if not isinstance(node, Join) or not node.on:
            raise NotLocal(type(node).__name__)
        sides = [(node.left, tuple(a for a, _ in node.on)), (node.right, tuple(b for _, b in node.on))]
        moved = [any(self.db[t].rows_between(since, version) for t in child.tables()) for child, _ in sides]
        out = []
        for i, (child, on) in enumerate(sides):  # the left delta meets the right side as it was, the right one the new left side
            if moved[i]:
                out += self._meeting(node, self._moves(child, since, version), on, self._held(*sides[1 - i], (since, version)[i]))
        return out

    @staticmethod
    def _meeting(node: Join, moves: list[Move], on: tuple[str, ...], held: HeldSide) -> list[Move]:
        holds = compiled(node.condition)[0] if node.condition else None
        out, made = [], 0
        for now, frags, m in moves:
            for (row, others), n in held.partners(tuple(now[c] for c in on)):
                both = now | dict(zip(held.columns, row))
                if holds is None or holds(both):
                    out.append((both, (*frags, *others), m * n))
                    made += abs(m * n)
            if made > MOST_DELTA:
                raise TooLarge("in memory: too large a delta")
        return out

    def _held(self, child: Node, on: tuple[str, ...], version: int) -> HeldSide:
        """A side of a join at a version; it is read once, then kept by its own deltas while these are on the driver."""
        side = self.sides.get((child, on))
        if side is not None and side.index is not None and side.version != version:
            try:
                moves = self._moves(child, side.version, version) if side.version < version else None
            except NotLocal:
                moves = None
            side = side.moved(moves, version) if moves is not None else None
        if side is None:
            side = self.sides[child, on] = HeldSide.of(full(self.db, child, self.phi, version), on, version)
        if side.index is None:
            raise NotLocal("too large a side of a join")
        return side

    @staticmethod
    def _argument(f: str, value: Any) -> Any:
        return value if f in ("count", "min", "max") else scaled(exact(value))

    def apply(self, delta: list[tuple]) -> dict[int, int]:
        """Move the state on by rows; returns what that adds to the counters."""
        changes: dict[int, int] = {}
        gone: list[tuple] = []
        come: list[tuple] = []
        before: dict[tuple, tuple | None] = {}
        for key, args, frags, m in delta:
            g = self._group(key)
            if key not in before:  # the old image is kept once for each touched group
                before[key] = self._taken(key, g)
            g.cnt += m
            if self.keyed is None:
                for f in frags:
                    n = g.frags.get(f, 0) + m
                    if n:
                        g.frags[f] = n
                    else:
                        del g.frags[f]
            for j, i in enumerate(self.linear):
                if args[i] is not None:
                    g.nn[j] += m
                    if self.node.aggs[i][1] != "count":
                        g.sums[j] += args[i] * m
            for j, i in enumerate(self.ordered):
                if args[i] is not None:
                    self._value(g, j, _ordered(args[i]), m)
        for key, old in before.items():
            self._put(key, self.groups[key], old, gone, come, changes)
        if self.top:
            self._count_top(gone, come, changes)
        return changes

    def advance(self, delta: Iterable[tuple[tuple, Group]]) -> dict[int, int]:
        """The same by what is added to each group, of which few are looked at together."""
        changes: dict[int, int] = {}
        gone: list[tuple] = []
        come: list[tuple] = []
        for key, d in delta:
            g = self._group(key)
            old = self._taken(key, g)
            g.cnt += d.cnt
            for f, m in d.frags.items() if self.keyed is None else ():
                n = g.frags.pop(f, 0) + m
                if n:
                    g.frags[f] = n
            for j in range(len(self.linear)):
                g.nn[j] += d.nn[j]
                g.sums[j] += d.sums[j]
            for j, found in enumerate(d.values):
                for v, m in found.items():
                    if m:
                        self._value(g, j, v, m)
            self._put(key, g, old, gone, come, changes)
            if self.entries > MOST_STATE:  # goes to tables, which start from the new version
                return {}
            if len(gone) + len(come) > MOST_DELTA:
                self._count_top(gone, come, changes)
                gone, come = [], []
        if self.top:
            self._count_top(gone, come, changes)
        return changes

    def _group(self, key: tuple) -> Group:
        g = self.groups.get(key)
        if g is None:
            if any(x != x for x in key):
                raise UnsupportedForMaintenance("in memory: NaN as a group key")
            g = self.groups[key] = self._new()
            self.entries += 1
        return g

    def _taken(self, key: tuple, g: Group) -> tuple | None:
        """A group's old image, before it changes."""
        self.entries -= g.entries()
        row = self._row(key, g)
        return None if row is None else (row, self._frags(key, g))

    def _put(self, key: tuple, g: Group, old: tuple | None, gone: list[tuple], come: list[tuple], changes: dict[int, int]) -> None:
        """What the change of a group, from its old image, does to the counters or to a top-k's input."""
        if g.cnt < 0:
            raise ValueError("a row is deleted more often than it occurs")
        new = self._row(key, g)
        after = None if new is None else (new, self._frags(key, g))
        if old != after:
            for sign, found, items in ((-1, old, gone), (1, after, come)):
                if found is not None and self.top:
                    items.append(self._item(*found))
                elif found is not None:
                    self._count(found[1], sign, changes)
        if g.cnt:
            self.entries += g.entries()
        else:
            del self.groups[key]

    @staticmethod
    def _value(g: Group, j: int, v: Any, m: int) -> None:
        n = g.values[j].get(v, 0) + m
        if n and v not in g.values[j]:
            bisect.insort(g.sorted[j], v)
        if n:
            g.values[j][v] = n
        else:
            del g.values[j][v]
            g.sorted[j].pop(bisect.bisect_left(g.sorted[j], v))

    def state_bytes(self) -> int:
        """An estimate: 64 bytes for each group, and 24 for each of its entries; of state tables, what is on the driver."""
        return sum(64 + 24 * (len(g.frags) + 2 * len(g.sums) + 2 * sum(map(len, g.values))) for g in self.groups.values()) + 64 * len(self.rows) + sum(64 * x.rows for x in self.sides.values() if x.index)
