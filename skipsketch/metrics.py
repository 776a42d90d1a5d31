"""Cost and accuracy measures."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable
from typing import Any

from pyspark.sql import DataFrame

from skipsketch.functions.ranges import ranges_bytes, sketch_bytes  # noqa: F401
from skipsketch.operators.aggregate import AggregateOp
from skipsketch.operators.maintain import Sketch
from skipsketch.operators.topk import TopKOp


def timed(work: Callable[[], Any], repeats: int = 10) -> dict[str, float]:
    """Median seconds, and the spread of the middle half of the repetitions against it."""
    found = []
    for _ in range(repeats):
        began = time.perf_counter()
        work()
        found.append(time.perf_counter() - began)
    q = statistics.quantiles(found, n=4) if len(found) > 1 else [found[0]] * 3
    return {"median": statistics.median(found), "spread": (q[2] - q[0]) / max(1e-9, statistics.median(found))}


def speedup(full_seconds: float, incremental_seconds: float) -> float:
    return full_seconds / incremental_seconds


def break_even(incremental: Callable[[float], float], full: Callable[[float], float], low: float = 0.0, high: float = 1.0, steps: int = 6) -> float:
    """The share of a table from which full maintenance is faster, by bisection; ``high`` if it never is."""
    if incremental(high) <= full(high):
        return high
    for _ in range(steps):
        middle = (low + high) / 2
        if incremental(middle) <= full(middle):
            low = middle
        else:
            high = middle
    return (low + high) / 2


def state_bytes(sketch: Sketch) -> int:
    """Size of all operator state files."""
    total = 0
    for op in sketch.ops.values():
        if isinstance(op, TopKOp):
            total += op.state.bytes()
        elif isinstance(op, AggregateOp):
            total += sum(s.bytes() for s in op.state.all())
    return total


def is_sound(maintained: set[int], accurate: set[int]) -> bool:
    """Every fragment that is needed is in the sketch."""
    return accurate <= maintained


def over_approximation(maintained: set[int], accurate: set[int]) -> float:
    return len(maintained) / max(1, len(accurate))


def same_bag(a: DataFrame, b: DataFrame) -> bool:
    """Equality with multiplicities, in one aggregation."""
    from skipsketch.sources.delta import delta_between

    return delta_between(a, b.select(*a.columns)).isEmpty()


def coverage(table: DataFrame, sketch: Sketch, name: str) -> tuple[int, int]:
    """Rows of a table in the sketch's fragments, and all its rows."""
    condition = sketch.phi.ranges[name].predicate(sketch.by_table()[name])
    from pyspark.sql import functions as F

    r = table.agg(F.count(F.when(condition, 1)).alias("a"), F.count("*").alias("b")).first()
    return r["a"], r["b"]
