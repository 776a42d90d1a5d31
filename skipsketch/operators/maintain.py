"""Capture of a sketch with its operator state, its use, and its maintenance by deltas.

The same operator code runs a whole table and a delta.  Joins are maintained by one of three expansions:

    before     dL * R_old + L_old * dR + dL * dR
    after      dL * R_new + L_new * dR - dL * dR
    telescoped dL * R_old + L_new * dR            (one term for each side, so n for n tables)

A maintained sketch has the same counters as a fresh capture, unless bounded state gave them up.
"""

from __future__ import annotations

import copy
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skipsketch.functions.bloom import BloomIndex
from skipsketch.functions.ranges import GridRanges, Partitioning, RangeSet, restrict
from skipsketch.operators import annotated as an
from skipsketch.operators.aggregate import AggregateOp
from skipsketch.operators.annotated import Annotated
from skipsketch.operators.topk import TopKOp
from skipsketch.plans.algebra import Aggregate, Distinct, Filter, Join, M, Node, Project, Scan, TopK, UnsupportedForMaintenance
from skipsketch.plans.safety import output_columns, pushable_predicates
from skipsketch.sources.delta import Database, dealt, expand
from skipsketch.sources.state import AdditiveState

#: Delta rows up to which that side of a join is broadcast; their number is known from the log.
BROADCAST_ROWS = 100_000


@dataclass
class Options:
    side: str = "telescoped"  # or before, after
    bloom: bool = False
    pushdown: bool = True
    limit: int | None = None  # rows kept by top-k, and values by minimum and maximum
    batch_rows: int | None = None  # a longer delta is taken in steps of whole versions, a longer version in parts of hashed rows


@dataclass
class Measures:
    delta_rows: int = 0
    fetched: int = 0
    joined: int = 0
    recaptured: int = 0


@dataclass
class Sketch:
    """A captured sketch: per fragment the number of result rows that need it, and the operators with their state."""

    plan: Node
    phi: Partitioning
    version: int
    counters: dict[int, int]
    ops: dict[Node, object] = field(default_factory=dict)
    blooms: dict[Node, dict[str, BloomIndex]] = field(default_factory=dict)
    options: Options = field(default_factory=Options)
    measures: Measures = field(default_factory=Measures)
    overlay: Sketch | None = None  # the same with changes that aren't committed yet

    @property
    def fragments(self) -> set[int]:
        """What queries must read; with uncommitted changes what they need too."""
        own = {f for f, n in self.counters.items() if n > 0}
        return own if self.overlay is None else self.overlay.fragments

    def forked(self) -> Sketch:
        """A copy that can be maintained by itself."""
        ops = {}
        for node, op in self.ops.items():
            ops[node] = copy.copy(op)
            ops[node].restore(op.snapshot())
        return replace(self, counters=dict(self.counters), ops=ops, blooms={n: dict(b) for n, b in self.blooms.items()}, measures=Measures(), overlay=None)

    def by_table(self) -> dict[str, set[int]]:
        return self.phi.split(self.fragments)


def _op(sketch: Sketch | None, db: Database, node: Node, phi: Partitioning, options: Options):  # noqa: ANN202
    if sketch is not None and node in sketch.ops:
        return sketch.ops[node]
    if isinstance(node, TopK):
        op = TopKOp(db.spark, node, options.limit)
    elif isinstance(node, Aggregate):
        op = AggregateOp(db.spark, node, phi, options.limit)
    else:
        op = AggregateOp(db.spark, Aggregate(node.child, tuple(output_columns(node.child)), ()), phi)
    if sketch is not None:
        sketch.ops[node] = op
    return op


def full(db: Database, node: Node, phi: Partitioning, version: int, sketch: Sketch | None = None, options: Options | None = None) -> Annotated:
    """The annotated result at a version; with a ``sketch`` the operators also note their state."""
    options = options or (sketch.options if sketch else Options())

    def run(n: Node) -> Annotated:
        if isinstance(n, Scan):
            return an.scan(n, db[n.table].image(version), phi)
        if (out := an.stateless(n, run)) is not None:
            return out
        if isinstance(n, Join):
            return an.join(run(n.left), run(n.right), n)
        op = _op(sketch, db, n, phi, options)
        return op.full(run(n.child)) if sketch is None else op.capture(run(n.child), version)

    return run(node)


def fragment_counts(result: Annotated) -> dict[int, int]:
    """Result rows for each fragment; at most as many rows as fragments reach the driver."""
    if len(result.thin) == 1 and not result.wide:
        rows = result.df.groupBy(F.col(result.thin[0]).alias("frag")).agg(F.sum(M).alias("n"))
    else:
        rows = result.df.select(F.explode(result.sketch()).alias("frag"), M).groupBy("frag").agg(F.sum(M).alias("n"))
    return {r["frag"]: r["n"] for r in rows.collect() if r["n"]}


def capture(db: Database, plan: Node, phi: Partitioning, version: int | None = None, options: Options | None = None, ops: dict[Node, object] | None = None) -> Sketch:
    """The accurate sketch at a version, with the state that maintenance needs; ``ops``: operators to be used."""
    version = db.version if version is None else version
    sketch = Sketch(plan, phi, version, {}, dict(ops or {}), options=options or Options())
    sketch.counters = fragment_counts(full(db, plan, phi, version, sketch))
    if sketch.options.bloom:
        for j in (n for n in plan.walk() if isinstance(n, Join) and n.on):
            found = {}
            for side, child, keys in (("left", j.left, [a for a, _ in j.on]), ("right", j.right, [b for _, b in j.on])):
                rows = full(db, child, Partitioning(), version).df.select(*keys)
                found[side] = BloomIndex.build(rows, keys, max(1000, rows.count()))
            sketch.blooms[j] = {s: BloomIndex(_stored(i.words), i.bits, i.hashes) for s, i in found.items()}
    return sketch


def _stored(df: DataFrame) -> DataFrame:
    from skipsketch.sources.shared import stored

    return stored(df, "bloom")


def recapture_fragments(db: Database, plan: Node, phi: Partitioning, version: int | None = None) -> set[int]:
    """The accurate sketch without state, for full maintenance: the plan once, and no more."""
    version = db.version if version is None else version
    return set(fragment_counts(full(db, plan, phi, version)))


def is_stale(sketch: Sketch, db: Database) -> bool:
    """Whether a table that the plan reads has changed; metadata only."""
    return any(db[t].version > sketch.version for t in sketch.plan.tables())


def known_rows(node: Node, rows: dict[str, int]) -> int | None:
    """An upper bound of a node's delta rows from those of its tables; None where a join may multiply them."""
    if isinstance(node, Scan):
        return rows.get(node.table, 0)
    if isinstance(node, Join):
        return None
    below = [known_rows(c, rows) for c in node.children()]
    if None in below:
        return None
    if isinstance(node, TopK):
        return 2 * node.k
    return sum(below) * (2 if isinstance(node, (Aggregate, Distinct)) else 1)


def delta_of(db: Database, sketch: Sketch, version: int | None = None, extra: dict[str, DataFrame] | None = None) -> Annotated | None:
    """The annotated delta of the sketch's plan since its version, None if nothing changed; moves its operators' state on.

    A table's delta of more than ``batch_rows`` rows is dealt out in parts by a hash of its rows, one for each task.  A part
    is folded by itself, and only what the parts add to their groups meets, once, in the state.
    """
    version = db.version if version is None else version
    phi, o, m, since = sketch.phi, sketch.options, sketch.measures, sketch.version
    extra = extra or {}
    rows_of = {t: db[t].rows_between(since, version) for t in sketch.plan.tables()}
    changed = {t for t, n in rows_of.items() if n or t in extra}
    m.delta_rows = sum(rows_of.values())
    if not changed:
        return None
    below_joins = {id(x) for n in sketch.plan.walk() if isinstance(n, Join) for c in n.children() for x in c.walk()}

    def log(n: Scan) -> DataFrame:
        rows = db[n.table].changes(since, version)
        if n.table in extra:
            rows = rows.unionByName(extra[n.table])
        for p in pushable_predicates(sketch.plan, n.table) if o.pushdown else ():
            rows = rows.where(F.expr(p))
        most = o.batch_rows
        return dealt(rows, -(-rows_of[n.table] // most)) if most and rows_of[n.table] > most else rows

    def new_image(n: Scan) -> DataFrame:
        rows = db[n.table].image(version)
        return rows.unionByName(extra[n.table]) if n.table in extra else rows

    def image(n: Node, new: bool) -> Annotated:
        def run(x: Node) -> Annotated:
            if isinstance(x, Scan):
                return an.scan(x, new_image(x) if new else db[x.table].image(since), phi)
            if (out := an.stateless(x, run)) is not None:
                return out
            if isinstance(x, Join):
                return an.join(run(x.left), run(x.right), x)
            if not new and isinstance(sketch.ops.get(x), AggregateOp) and o.limit is None:
                op = sketch.ops[x]
                return op.result(*old_images.get(x, op.held()))
            return _op(None, db, x, phi, Options()).full(run(x.child))

        return run(n)

    old_images: dict[Node, tuple] = {}  # of aggregations below joins, the state before its delta

    def touched(n: Node) -> bool:
        return any(t in changed for t in n.tables())

    def delta(n: Node) -> Annotated:
        if isinstance(n, Scan):
            return an.scan(n, log(n), phi)
        if (out := an.stateless(n, delta)) is not None:
            return out
        if isinstance(n, Join):
            return joined(n)
        op = sketch.ops[n]
        if isinstance(op, AggregateOp) and id(n) in below_joins and o.limit is None:
            old_images[n] = op.held()  # frames over the parts that were there then
        if isinstance(op, TopKOp):
            out = op.maintain(delta(n.child), version, lambda: image(n.child, True))
        else:
            def again(groups: DataFrame) -> Annotated:
                rows = image(n.child, True)
                keys = F.lit(True)
                for c in groups.columns:
                    keys = keys & F.col(c).eqNullSafe(F.col(f"__g_{c}"))
                return Annotated(rows.df.join(groups.select(*(F.col(c).alias(f"__g_{c}") for c in groups.columns)), keys, "left_semi"), rows.thin, rows.wide)

            out = op.maintain(delta(n.child), version, again)
        m.recaptured += op.recaptured
        op.recaptured = 0
        return out

    def joined(n: Join) -> Annotated:
        dl = delta(n.left) if touched(n.left) else None
        dr = delta(n.right) if touched(n.right) else None
        if o.bloom and n in sketch.blooms:
            ka, kb, index = [a for a, _ in n.on], [b for _, b in n.on], sketch.blooms[n]
            if dr is not None:  # what is inserted on one side is in its filter before the other side is tested
                index["right"] = _extended(index["right"], dr, kb)
            if dl is not None:
                index["left"] = _extended(index["left"], dl, ka)
            if dl is not None:
                dl = _probed(dl, index["right"], ka, m)
            if dr is not None:
                dr = _probed(dr, index["left"], kb, m)

        def small(side: str, child: Node) -> str:
            """The side, where its delta is known to be small enough to broadcast; else Spark decides by sizes."""
            most = None if extra else known_rows(child, rows_of)
            return side if most is not None and most <= BROADCAST_ROWS else ""

        left_small, right_small = small("left", n.left), small("right", n.right)
        parts = []
        if dl is not None and dr is None:
            return an.join(dl, image(n.right, False), n, small=left_small)
        if dr is not None and dl is None:
            return an.join(image(n.left, False), dr, n, small=right_small)
        if o.side == "telescoped":
            parts = [an.join(dl, image(n.right, False), n, small=left_small), an.join(image(n.left, True), dr, n, small=right_small)]
        else:
            new = o.side == "after"
            parts = [an.join(dl, image(n.right, new), n, small=left_small), an.join(image(n.left, new), dr, n, small=right_small), an.join(dl, dr, n, sign=-1 if new else 1)]
        return an.union(*parts)

    return delta(sketch.plan)


def maintain(db: Database, sketch: Sketch, version: int | None = None, extra: dict[str, DataFrame] | None = None) -> dict[int, int]:
    """Bring the sketch to a version; returns its delta, fragment -> +1 or -1.

    ``extra`` has signed rows of a transaction that isn't committed yet, by table.  They go into an overlay only: the
    sketch's own counters and state stay those of committed versions, so nothing counts twice after the commit.
    A delta that is refused leaves the sketch as it was.
    """
    version = db.version if version is None else version
    before = sketch.fragments
    sketch.overlay = None
    saved = {n: op.snapshot() for n, op in sketch.ops.items()}, dict(sketch.counters), {n: dict(b) for n, b in sketch.blooms.items()}, sketch.version
    try:
        for until in steps(db, sketch, version):
            found = delta_of(db, sketch, until)
            merged(sketch.counters, fragment_counts(found) if found is not None else {})
            sketch.version = until
    except Exception:
        states, sketch.counters, sketch.blooms, sketch.version = saved
        for n, op in sketch.ops.items():
            op.restore(states[n])
        raise
    if extra:
        over = sketch.forked()
        found = delta_of(db, over, version, extra)
        merged(over.counters, fragment_counts(found) if found is not None else {})
        sketch.overlay = over
    after = sketch.fragments
    return {f: 1 if f in after else -1 for f in before ^ after}


def steps(db: Database, sketch: Sketch, version: int) -> list[int]:
    """Versions to go to one after the other, each with at most ``batch_rows`` delta rows as far as versions allow.

    A single version that is longer is one step, whose rows ``delta_of`` deals out in parts.
    """
    most, tables = sketch.options.batch_rows, sketch.plan.tables()
    if most is None:
        return [version]
    out: list[int] = []
    rows = 0
    for v in range(sketch.version + 1, version + 1):
        here = sum(db[t].rows_between(v - 1, v) for t in tables)
        if rows and rows + here > most:
            out.append(v - 1)
            rows = 0
        rows += here
    return [*out, version]


def merged(counters: dict[int, int], changes: dict[int, int]) -> dict[int, int]:
    """Add to the counters; fragments whose counter left or reached zero are the sketch's delta."""
    out = {}
    for f, n in changes.items():
        before = counters.get(f, 0)
        after = before + n
        if after < 0:
            raise ValueError("a fragment is needed by fewer than no rows")
        if (before > 0) != (after > 0):
            out[f] = 1 if after else -1
        if after:
            counters[f] = after
        else:
            counters.pop(f, None)
    return out


def _extended(index: BloomIndex, delta: Annotated, key: list[str]) -> BloomIndex:
    new = index.insert(delta.df.where(F.col(M) > 0).select(*key), key)
    return BloomIndex(_stored(new.words), new.bits, new.hashes)


def _probed(delta: Annotated, index: BloomIndex, key: list[str], m: Measures) -> Annotated:
    from skipsketch.sources.shared import stored

    m.fetched += delta.df.count()
    kept = stored(index.keep(delta.df, key), "probed")
    m.joined += kept.count()
    return Annotated(kept, delta.thin, delta.wide)


def with_sketch(db: Database, sketch: Sketch, version: int | None = None, plan: Node | None = None, extra: dict[str, DataFrame] | None = None) -> DataFrame:
    """The answer over the sketch's fragments only; the conditions reach the files' statistics."""
    return answer(db, plan or sketch.plan, version, {t: (sketch.phi.ranges[t], f) for t, f in sketch.by_table().items()}, extra)


def answer(db: Database, plan: Node, version: int | None = None, only: dict[str, tuple] | None = None, extra: dict[str, DataFrame] | None = None) -> DataFrame:
    """The plan's plain rows at a version.

    ``only`` has the ranges and fragments to which tables are restricted, ``extra`` signed rows that aren't committed.
    """
    version = db.version if version is None else version
    none = Partitioning()

    def run(n: Node) -> Annotated:
        if isinstance(n, Scan):
            rows = db[n.table].image(version)
            if extra and n.table in extra:
                rows = rows.unionByName(extra[n.table].select(*rows.columns))
            return an.scan(n, restrict(rows, *only[n.table]) if only and n.table in only else rows, none)
        if (out := an.stateless(n, run)) is not None:
            return out
        if isinstance(n, Join):
            return an.join(run(n.left), run(n.right), n)
        return _op(None, db, n, none, Options()).full(run(n.child))

    out = run(plan)
    rows = out.df.select(*out.columns, M)
    if _single(plan) or not extra and all(db[t].rows_between(db[t].first, version) == 0 for t in plan.tables()) and not any(isinstance(n, TopK) for n in plan.walk()):
        return rows.drop(M)  # every row stands for one
    return expand(rows.groupBy(*out.columns).agg(F.sum(M).alias(M)))


def _single(plan: Node) -> bool:
    """Whether each result row has the multiplicity 1, by the plan alone."""
    return isinstance(plan, (Aggregate, Distinct)) or isinstance(plan, (Filter, Project)) and _single(plan.child)


def rebalance(sketch: Sketch, ranges: RangeSet | GridRanges, moves: dict[int, set[int]]) -> None:
    """Carry a sketch and its state over to ``ranges``, in which some of its table's ranges were split or merged.

    A count can't be split, so both halves of a range keep it, and a row counted in two merged ranges stays
    counted twice: the sketch may cover more than it needs until it is captured again, never less.
    """
    old, name = sketch.phi, ranges.table
    new = Partitioning(*(ranges if t == name else r for t, r in old.ranges.items()))

    def moved(fragment: int) -> list[int]:
        t, f = old.local(fragment)
        return [new.offset[t] + x for x in (sorted(moves[f]) if t == name else [f])]

    counters: dict[int, int] = {}
    for f, n in sketch.counters.items():
        for x in moved(f):
            counters[x] = counters.get(x, 0) + n
    pairs = [(f, x) for f in range(old.size) for x in moved(f)]
    for op in sketch.ops.values():
        if isinstance(op, TopKOp):
            raise UnsupportedForMaintenance("capture a top-k again after its ranges changed")
        op.phi = new
        if op.state.frags is not None:
            table = F.broadcast(op.spark.createDataFrame(pairs, "frag int, __new int"))  # a row for each fragment
            rows = op.state.frags.read().join(table, "frag").drop("frag").withColumnRenamed("__new", "frag")
            fresh = AdditiveState(op.spark, op.state.frags.keys, ["cnt"])
            fresh.add(sketch.version, rows.groupBy(*fresh.keys).agg(F.sum("cnt").alias("cnt")))
            op.state.frags = fresh
    sketch.phi, sketch.counters = new, counters


def supported(plan: Node) -> None:
    known = {"Scan", "Filter", "Project", "Join", "Aggregate", "Distinct", "TopK", "UnionAll"}
    for n in plan.walk():
        if type(n).__name__ not in known:
            raise UnsupportedForMaintenance(type(n).__name__)
