"""The query manager: finds, captures, maintains and uses sketches; and when it does so."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skipsketch.functions.ranges import GridRanges, Partitioning, RangeSet, annotate, equi_depth_ranges, merge_ranges, split_range
from skipsketch.operators.memory import MOST_DELTA, MemorySketch
from skipsketch.operators.maintain import Options, Sketch, answer, capture, is_stale, maintain, rebalance, recapture_fragments, supported, with_sketch
from skipsketch.operators.topk import TopKOp
from skipsketch.plans.algebra import Aggregate, Distinct, M, Node, TopK, UnsupportedForMaintenance, template_key
from skipsketch.plans.safety import choose_attribute, is_safe
from skipsketch.sources.catalog import SketchStore
from skipsketch.sources.delta import Database


@dataclass
class Loads:
    """Rows of each range of a table, estimated by the deltas since they were counted."""

    rows: dict[int, int]
    version: int
    start: int
    changed: int = 0
    stuck: set[int] = field(default_factory=set)  # ranges of one value, that can't be split

    @staticmethod
    def counted(db: Database, ranges: RangeSet) -> Loads:
        rows = _by_range(db[ranges.table].image(), ranges)
        return Loads(rows, db[ranges.table].version, sum(rows.values()))

    def follow(self, db: Database, ranges: RangeSet) -> None:
        table = db[ranges.table]
        if table.version > self.version:
            for f, n in _by_range(table.changes(self.version), ranges).items():
                self.rows[f] = self.rows.get(f, 0) + n
            self.changed += table.rows_between(self.version)
            self.version = table.version

    def step(self, db: Database, ranges: RangeSet, factor: float) -> tuple[str, RangeSet, dict[int, set[int]]] | None:
        """The next split or merge that is due."""
        n = [self.rows.get(f, 0) for f in range(ranges.count)]
        mean = max(1.0, sum(n) / ranges.count)
        for f in sorted(range(ranges.count), key=n.__getitem__, reverse=True):
            if n[f] <= factor * mean:
                break
            if f in self.stuck:
                continue
            inside = db[ranges.table].image().where(ranges.predicate({f})).where(F.col(M) > 0)
            lowest, middle = inside.agg(F.min(ranges.attr), F.percentile_approx(ranges.attr, 0.5)).first()
            if middle is None or middle <= lowest:  # half of it is one value: cut after that
                middle = None if lowest is None else inside.where(F.col(ranges.attr) > F.lit(lowest)).agg(F.min(ranges.attr)).first()[0]
            if middle is None:
                self.stuck.add(f)
                continue
            return "split", *split_range(ranges, f, middle)
        for f in range(ranges.count - 1):
            if ranges.count > 2 and n[f] + n[f + 1] < mean / factor:
                return "merged", *merge_ranges(ranges, f)
        return None

    def moved(self, moves: dict[int, set[int]], kind: str) -> None:
        rows: dict[int, int] = {}
        for f, to in moves.items():
            for x in to:  # halves of a split range are taken as equal
                rows[x] = rows.get(x, 0) + self.rows.get(f, 0) // len(to)
        self.rows = rows
        self.stuck = set().union(*(moves[f] for f in self.stuck)) if self.stuck else set()


def _by_range(rows: DataFrame, ranges: RangeSet) -> dict[int, int]:
    """Net rows of each range; as many rows as ranges reach the driver."""
    found = annotate(rows, ranges).groupBy("__frag").agg(F.sum(M).alias("n"))
    return {r["__frag"]: r["n"] for r in found.collect()}


Ranges = RangeSet | GridRanges


@dataclass
class Strategy:
    """What happens after an update; queries always see a fresh sketch."""

    name: str = "lazy"
    batch_size: int = 1  # eager: delta rows to wait for
    pinned: set[str] = field(default_factory=set)  # hybrid: templates maintained at once
    idle: Callable[[], bool] = lambda: False  # hybrid: whether now is a good time for the others


def LazyStrategy() -> Strategy:  # noqa: N802
    return Strategy("lazy")


def EagerStrategy(batch_size: int = 1) -> Strategy:  # noqa: N802
    return Strategy("eager", batch_size)


def HybridStrategy(pinned: set[str], idle: Callable[[], bool]) -> Strategy:  # noqa: N802
    return Strategy("hybrid", pinned=pinned, idle=idle)


def FullMaintenance() -> Strategy:  # noqa: N802
    """Baseline: capture again whenever a stale sketch is needed."""
    return Strategy("full")


def NoSketch() -> Strategy:  # noqa: N802
    """Baseline: run every query as it is."""
    return Strategy("none")


class Session:
    """``ranges``: for each table that may be sketched its partition, or several to choose from; ``positive``: expressions never negative.

    ``backend``: tables, memory, or auto, which keeps state in memory while it and the deltas are within the
    bounds of ``operators.memory`` and goes to state tables beyond them.  ``clustered``: the column by which a
    table's files are sorted, preferred where several attributes are safe.  ``balance_share``: after changes of so
    large a share of a table's rows its ranges are balanced (``balance``); None leaves them as they are.
    """

    def __init__(self, spark: SparkSession, tables: dict[str, DataFrame], ranges: dict[str, Ranges | list[Ranges]], strategy: Strategy | None = None, options: Options | None = None, positive: set[str] = frozenset(), persist: bool = False, backend: str = "tables", clustered: dict[str, str] | None = None, balance_share: float | None = None):
        self.spark, self.db = spark, Database(spark, tables)
        self.ranges = {t: r if isinstance(r, list) else [r] for t, r in ranges.items()}
        self.strategy, self.options = strategy or LazyStrategy(), options or Options()
        self.positive, self.persist, self.backend, self.clustered, self.balance_share = positive, persist, backend, clustered or {}, balance_share
        self.store = SketchStore(spark)
        self.pending: dict[str, int] = {}
        self.loads: dict[tuple[str, str], Loads] = {}  # rows of each range, by table and attribute
        self.counts = {"captured": 0, "maintained": 0, "recaptured": 0, "reused": 0, "derived": 0, "plain": 0, "split": 0, "merged": 0, "renewed": 0}

    def partitioning(self, plan: Node) -> Partitioning:
        """For each table the ranges of the attribute that suits the plan best, of those on which a sketch is safe."""
        safe = []
        for t in plan.tables():
            own = self.ranges.get(t, [])
            grids = [r for r in own if isinstance(r, GridRanges)]
            plain = {r.attr: r for r in own if isinstance(r, RangeSet)}
            best = choose_attribute(plan, t, list(plain), self.positive, self.clustered.get(t))
            if best is not None:
                safe.append(plain[best])
            else:
                safe += [g for g in grids if all(is_safe(plan, t, p.attr, self.positive) for p in g.parts)][:1]
        return Partitioning(*safe)

    def query(self, plan: Node, extra: dict[str, DataFrame] | None = None) -> DataFrame:
        """The plan's answer at the newest version, over a sketch where one is safe.

        ``extra``: signed rows, by table, that this query's transaction has changed and not committed.
        """
        supported(plan)
        phi = self.partitioning(plan)
        if extra:
            return self._uncommitted(plan, phi, extra)
        if self.strategy.name == "none" or not phi.ranges:
            self.counts["plain"] += 1
            return answer(self.db, plan)
        if self.strategy.name == "full":
            return self._full(plan, phi)
        found = self.store.find(plan)
        if found is None and (derived := self._derived(plan, phi)) is not None:
            return with_sketch(self.db, derived)
        if found is None:
            found = f"sketch-{len(self.store.entries)}"
            self.store.put(found, self._capture(plan, phi), self.persist)
            self.counts["captured"] += 1
        else:
            self.counts["reused"] += 1
        sketch = self.store.get(found)
        if is_stale(sketch, self.db):
            self._maintain(found)
        return with_sketch(self.db, sketch, plan=plan)

    def _uncommitted(self, plan: Node, phi: Partitioning, extra: dict[str, DataFrame]) -> DataFrame:
        """Over the stored sketch with an overlay; the stored one stays that of committed versions."""
        found = self.store.find(plan)
        sketch = self.store.get(found) if found else None
        if not isinstance(sketch, Sketch) or not sketch.ops and any(isinstance(n, (Aggregate, Distinct, TopK)) for n in plan.walk()):
            return answer(self.db, plan, extra=extra)
        maintain(self.db, sketch, extra={t: d for t, d in extra.items() if t in plan.tables()})
        out = with_sketch(self.db, sketch, plan=plan, extra=extra)
        sketch.overlay = None
        return out

    def _derived(self, plan: Node, phi: Partitioning) -> Sketch | None:
        """A sketch for other constants above the same groups, from state in memory and without reading a table."""
        for sketch_id, held in list(self.store.live.items()):
            if not isinstance(held, MemorySketch) or held.phi.ranges != phi.ranges or not held.serves(plan):
                continue
            if is_stale(held, self.db):
                self._maintain(sketch_id)
                held = self.store.get(sketch_id)
            if isinstance(held, MemorySketch):
                self.counts["derived"] += 1
                return Sketch(plan, phi, held.version, dict.fromkeys(held.fragments_for(plan), 1))
        return None

    def _capture(self, plan: Node, phi: Partitioning) -> Sketch | MemorySketch:
        if self.backend != "tables":
            try:
                return MemorySketch(self.db, plan, phi, strict=True)
            except UnsupportedForMaintenance:
                if self.backend == "memory":
                    raise
        return capture(self.db, plan, phi, options=self.options)

    def _forget(self, sketch_id: str) -> None:
        self.store.entries.pop(sketch_id, None)
        self.store.live.pop(sketch_id, None)
        self.pending.pop(sketch_id, None)

    def _full(self, plan: Node, phi: Partitioning) -> DataFrame:
        found = self.store.find(plan)
        sketch = self.store.get(found) if found else None
        if sketch is None or is_stale(sketch, self.db):
            whole = self.store.get(found).plan if found else plan
            fragments = recapture_fragments(self.db, whole, phi)
            sketch = Sketch(whole, phi, self.db.version, dict.fromkeys(fragments, 1))
            found = found or f"sketch-{len(self.store.entries)}"
            self.store.entries.setdefault(found, []).append((self.db.version, ""))
            self.store.live[found] = sketch
            self.counts["recaptured"] += 1
        return with_sketch(self.db, sketch, plan=plan)

    def _maintain(self, sketch_id: str) -> dict[int, int]:
        sketch = self.store.get(sketch_id)
        if isinstance(sketch, MemorySketch):
            try:
                changes = sketch.maintain()
            except UnsupportedForMaintenance:  # too large a delta: capture again, on tables
                new = capture(self.db, sketch.plan, sketch.phi, options=self.options)
                changes = {f: 1 if f in new.fragments else -1 for f in new.fragments ^ sketch.fragments}
                sketch = new
                self.counts["recaptured"] += 1
            except Exception:  # its state may hold a part of the delta
                self._forget(sketch_id)
                raise
        else:
            changes = maintain(self.db, sketch)
        self.counts["maintained"] += 1
        self.pending[sketch_id] = 0
        self.store.put(sketch_id, sketch, self.persist)
        return changes

    def update(self, changes: dict[str, tuple[DataFrame | None, DataFrame | None]]) -> dict[str, dict[int, int]]:
        """Commit inserts and deletes; then what the strategy says.  Returns the sketch deltas it made."""
        self.db.update(changes)
        return self._after(set(changes))

    def update_rows(self, table: str, inserts: list[tuple] = (), deletes: list[tuple] = ()) -> dict[str, dict[int, int]]:
        """The same with a small delta given as rows, which stay on the driver until there are many."""
        self.db.version += 1
        log = self.db[table]
        log.commit_rows(self.db.version, inserts, deletes)
        out = self._after({table})
        if sum(map(len, log.recent.values())) > MOST_DELTA:
            log.flush()
        return out

    def update_delta(self, deltas: dict[str, DataFrame]) -> dict[str, dict[int, int]]:
        """The same with signed rows."""
        self.db.version += 1
        for name, delta in deltas.items():
            self.db[name].commit_delta(self.db.version, delta)
        return self._after(set(deltas))

    def balance(self, table: str, factor: float = 4.0, renew: float = 0.5) -> dict[str, int]:
        """Split ranges of more than ``factor`` times the mean number of rows and merge neighbours of less than a ``factor``-th.

        The rows of each range are counted once and then carried on from deltas.  Sketches are remapped, which keeps them
        sound; those whose state can't be split are captured again when they are needed.  Where more than the share
        ``renew`` of the rows changed since the ranges were made, new equi-depth ranges replace them.
        """
        done = {"split": 0, "merged": 0, "renewed": 0}
        for i, ranges in enumerate(self.ranges.get(table, [])):
            if not isinstance(ranges, RangeSet) or not ranges.cuts:
                continue
            loads = self.loads.get((table, ranges.attr)) or Loads.counted(self.db, ranges)
            loads.follow(self.db, ranges)
            if loads.changed > renew * max(1, loads.start):
                rows = self.db[table].image().where(F.col(M) > 0)
                new = equi_depth_ranges(rows, table, ranges.attr, ranges.count)
                if new != ranges:
                    self.ranges[table][i] = new
                    for sketch_id in [x for x in self.store.entries if self.store.get(x).phi.ranges.get(table) == ranges]:
                        self._forget(sketch_id)
                    done["renewed"] += 1
                self.loads[table, ranges.attr] = Loads.counted(self.db, new)
                continue
            while (step := loads.step(self.db, ranges, factor)) is not None:
                kind, new, moves = step
                loads.moved(moves, kind)
                self._moved(table, ranges, new, moves)
                self.ranges[table][i] = ranges = new
                done[kind] += 1
            self.loads[table, ranges.attr] = loads
        for kind, n in done.items():
            self.counts[kind] += n
        return done

    def _moved(self, table: str, old: RangeSet, new: RangeSet, moves: dict[int, set[int]]) -> None:
        for sketch_id in list(self.store.entries):
            sketch = self.store.get(sketch_id)
            if sketch.phi.ranges.get(table) != old:
                continue
            if isinstance(sketch, Sketch) and not any(isinstance(op, TopKOp) for op in sketch.ops.values()):
                rebalance(sketch, new, moves)
                self.store.put(sketch_id, sketch, self.persist)
            else:
                self._forget(sketch_id)

    def _after(self, tables: set[str]) -> dict[str, dict[int, int]]:
        out, s = {}, self.strategy
        for t in tables if self.balance_share is not None else ():
            for r in self.ranges.get(t, []):
                if isinstance(r, RangeSet):
                    loads = self.loads.get((t, r.attr))
                    if loads is None:
                        loads = self.loads[t, r.attr] = Loads.counted(self.db, r)
                    if self.db[t].rows_between(loads.version) > self.balance_share * max(1, sum(loads.rows.values())):
                        self.balance(t)
                        break
        if s.name not in ("eager", "hybrid"):
            return out
        for sketch_id in list(self.store.entries):
            sketch = self.store.get(sketch_id)
            mine = tables & set(sketch.plan.tables())
            if not mine:
                continue
            self.pending[sketch_id] = sum(self.db[t].rows_between(sketch.version) for t in sketch.plan.tables())
            now = self.pending[sketch_id] >= s.batch_size if s.name == "eager" else template_key(sketch.plan) in s.pinned or s.idle()
            if now:
                out[sketch_id] = self._maintain(sketch_id)
        return out
