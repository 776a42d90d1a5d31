"""The catalog of sketches: immutable versions by query template, in a shared folder."""

from __future__ import annotations

import datetime
import json
from dataclasses import asdict
from decimal import Decimal
from typing import Any

from pyspark.sql import SparkSession
from pyspark.sql import types as T

from skipsketch.functions.ranges import GridRanges, Partitioning, RangeSet
from skipsketch.operators.aggregate import AggregateOp, AggregateState
from skipsketch.operators.maintain import Measures, Options, Sketch
from skipsketch.operators.topk import TopKOp
from skipsketch.plans.algebra import Aggregate, Distinct, Node, TopK, from_json, template_key, to_json
from skipsketch.plans.safety import can_reuse, output_columns
from skipsketch.sources.shared import fresh_dir
from skipsketch.sources.state import AdditiveState


def _encoded(x: Any) -> Any:
    if isinstance(x, (datetime.datetime, datetime.date)):
        return {"time": x.isoformat(), "kind": type(x).__name__}
    return {"decimal": str(x)} if isinstance(x, Decimal) else x


def _decoded(x: Any) -> Any:
    if isinstance(x, dict) and "time" in x:
        return getattr(datetime, x["kind"]).fromisoformat(x["time"])
    return Decimal(x["decimal"]) if isinstance(x, dict) and "decimal" in x else x


def ranges_to_json(r: RangeSet | GridRanges) -> dict:
    if isinstance(r, GridRanges):
        return {"table": r.table, "parts": [ranges_to_json(p) for p in r.parts]}
    return {"table": r.table, "attr": r.attr, "cuts": [_encoded(c) for c in r.cuts]}


def ranges_from_json(d: dict) -> RangeSet | GridRanges:
    if "parts" in d:
        return GridRanges(d["table"], tuple(ranges_from_json(p) for p in d["parts"]))
    return RangeSet(d["table"], d["attr"], tuple(_decoded(c) for c in d["cuts"]))


def _state_json(s: AdditiveState) -> dict:
    return {"keys": s.keys, "sums": s.sums, "path": s.path, "parts": s.parts, "schema": s.schema.json() if s.schema else None}


def _state(spark: SparkSession, d: dict) -> AdditiveState:
    return AdditiveState(spark, d["keys"], d["sums"], d["path"], [tuple(p) for p in d["parts"]], T.StructType.fromJson(json.loads(d["schema"])) if d["schema"] else None)


def describe(sketch: Sketch) -> str:
    """All of a sketch as JSON: its states are files already, so this is what evicting it from memory keeps.

    A sketch whose state is in memory keeps its fragments; restored, it can be used but not maintained.
    """
    ops = []
    if not isinstance(sketch, Sketch):
        sketch = Sketch(sketch.plan, sketch.phi, sketch.version, sketch.counters)
    for n in dict.fromkeys(sketch.plan.walk()):
        op = sketch.ops.get(n)
        if isinstance(op, TopKOp):
            ops.append({"limit": op.limit, "horizon": [_encoded(x) for x in op.horizon] if op.horizon else None, "state": _state_json(op.state)})
        elif isinstance(op, AggregateOp):
            s = op.state
            ops.append({"limit": op.limit, "groups": _state_json(s.groups), "frags": _state_json(s.frags) if s.frags else None, "values": {k: _state_json(v) for k, v in s.values.items()}, "horizons": {k: _state_json(v) for k, v in s.horizons.items()}})
    return json.dumps({"plan": to_json(sketch.plan), "ranges": [ranges_to_json(r) for r in sketch.phi.ranges.values()], "version": sketch.version, "counters": {str(k): v for k, v in sketch.counters.items()}, "options": asdict(sketch.options), "ops": ops})


def restore(spark: SparkSession, text: str) -> Sketch:
    d = json.loads(text)
    phi = Partitioning(*(ranges_from_json(r) for r in d["ranges"]))
    plan: Node = from_json(d["plan"])
    options = Options(**(d["options"] | {"bloom": False}))  # filters are rebuilt by a new capture only
    sketch = Sketch(plan, phi, d["version"], {int(k): v for k, v in d["counters"].items()}, options=options, measures=Measures())
    todo = iter(d["ops"])
    for n in dict.fromkeys(plan.walk()):
        if isinstance(n, TopK):
            o = next(todo)
            op = TopKOp(spark, n, o["limit"])
            op.horizon = tuple(_decoded(x) for x in o["horizon"]) if o["horizon"] else None
            op.state = _state(spark, o["state"])
            sketch.ops[n] = op
        elif isinstance(n, (Aggregate, Distinct)):
            o = next(todo)
            node = n if isinstance(n, Aggregate) else Aggregate(n.child, tuple(output_columns(n.child)), ())
            op = AggregateOp(spark, node, phi, o["limit"])
            op.state = AggregateState(_state(spark, o["groups"]), _state(spark, o["frags"]) if o["frags"] else None, {k: _state(spark, v) for k, v in o["values"].items()}, {k: _state(spark, v) for k, v in o["horizons"].items()})
            sketch.ops[n] = op
    return sketch


class SketchStore:
    """Append-only: a put never changes an older version, so readers need no locks."""

    def __init__(self, spark: SparkSession, path: str = ""):
        self.spark, self.path = spark, path or fresh_dir(spark, "catalog")
        self.entries: dict[str, list[tuple[int, str]]] = {}
        self.live: dict[str, Sketch] = {}

    def put(self, sketch_id: str, sketch: Sketch, persist: bool = True) -> None:
        text = describe(sketch)
        self.entries.setdefault(sketch_id, []).append((sketch.version, text))
        self.live[sketch_id] = sketch
        if persist:
            row = [(sketch_id, template_key(sketch.plan), sketch.version, text)]
            self.spark.createDataFrame(row, "sketch_id string, template_key string, version long, definition string").coalesce(1).write.mode("append").parquet(self.path)

    def get(self, sketch_id: str) -> Sketch:
        """The newest version, from its files if it was evicted."""
        if sketch_id not in self.live:
            self.live[sketch_id] = restore(self.spark, self.entries[sketch_id][-1][1])
        return self.live[sketch_id]

    def at_version(self, sketch_id: str, version: int) -> Sketch:
        """The newest version not after ``version``."""
        found = [t for v, t in self.entries[sketch_id] if v <= version]
        if not found:
            raise KeyError(f"{sketch_id} has no version up to {version}")
        return restore(self.spark, found[-1])

    def history(self, sketch_id: str) -> list[int]:
        return [v for v, _ in self.entries[sketch_id]]

    def evict(self, sketch_id: str) -> None:
        self.live.pop(sketch_id, None)

    def vacuum(self, sketch_id: str, keep: int = 1) -> None:
        self.entries[sketch_id] = self.entries[sketch_id][-keep:]

    def load(self) -> None:
        """Read the entries that other sessions wrote."""
        rows = self.spark.read.parquet(self.path).orderBy("sketch_id", "version").toLocalIterator()
        self.entries = {}
        for r in rows:
            self.entries.setdefault(r["sketch_id"], []).append((r["version"], r["definition"]))

    def find(self, plan: Node) -> str | None:
        """A sketch that serves the plan: same template first, then the reuse test."""
        key = template_key(plan)
        for sketch_id in self.entries:
            stored = self.get(sketch_id).plan
            if template_key(stored) == key and can_reuse(stored, plan):
                return sketch_id
        return None
