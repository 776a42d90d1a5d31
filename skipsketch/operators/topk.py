"""Top-k in full and by delta.

State: the input's rows with sketch and multiplicity, all of them or the best ``limit``.  With a limit the worst
kept row is the horizon: what comes after it is not kept, and is not in the state either way, so deltas beyond
it are ignored.  When fewer than k rows remain and there is a horizon, the input is read again.

The head of the state, some more than k rows in order, is on the driver.  A delta meets it only where it lies not
after the head's last row, and only positions that changed are handed on; the state is read again when the head
runs short, not at each delta.  Ties are broken by all columns, in the query as in the sketch.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import cmp_to_key
from typing import Any

from pyspark.sql import Column, DataFrame, Row, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from skipsketch.operators.annotated import SK, Annotated
from skipsketch.plans.algebra import M, TopK
from skipsketch.sources.delta import consolidate
from skipsketch.sources.shared import stored
from skipsketch.sources.state import MOST_PARTS, AdditiveState


def order_columns(node: TopK, columns: list[str], sketch: bool = True) -> list[Column]:
    first = [F.desc_nulls_last(c) if down else F.asc_nulls_last(c) for c, down in node.order]
    return [*first, *(F.asc_nulls_last(c) for c in columns if c not in dict(node.order)), *([F.asc(SK)] if sketch else [])]


def cut(node: TopK, rows: DataFrame, columns: list[str], sketch: bool = True) -> DataFrame:
    """The first k rows by multiplicity ``cnt``, the last one's reduced to fit; k rows are enough to look at."""
    by = order_columns(node, columns, sketch)
    few = rows.where("cnt > 0").orderBy(*by).limit(node.k)
    before = F.coalesce(F.sum("cnt").over(Window.orderBy(*by).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return few.withColumn("__b", before).where(F.col("__b") < node.k).withColumn("cnt", F.least("cnt", F.lit(node.k) - F.col("__b"))).drop("__b")


def _compared(a: Any, b: Any, down: bool) -> int:
    """As Spark orders two values: nulls last either way, NaN above all numbers, text by code points."""
    if a is None or b is None:
        return (a is None) - (b is None)
    nan_a, nan_b = (isinstance(x, float) and x != x for x in (a, b))
    sign = int(nan_a) - int(nan_b) if nan_a or nan_b else (a > b) - (a < b)
    return -sign if down else sign


_NAN = float("nan")  # the one that rows hold, so that equal rows are equal


def _held(x: Any) -> Any:
    if isinstance(x, float) and x != x:
        return _NAN
    if isinstance(x, list):
        return tuple(map(_held, x))
    return bytes(x) if isinstance(x, bytearray) else x


class TopKOp:
    def __init__(self, spark: SparkSession, node: TopK, limit: int | None = None):
        if limit is not None and limit < node.k:
            raise ValueError("the limit must be k or more")
        self.spark, self.node, self.limit = spark, node, limit
        self.state: AdditiveState | None = None
        self.horizon: tuple | None = None
        self.head: list[tuple[tuple, int]] | None = None  # rows (columns and sketch) with their counts, in order
        self.bound: tuple | None = None  # the head's last row, None where the head is all of the state
        self.recaptured, self.refilled = 0, 0

    @property
    def room(self) -> int:
        """Rows of the head after it was read; it may grow to twice as many."""
        return 2 * self.node.k + 20

    def _emit(self, rows: DataFrame, columns: list[str], sign: int) -> DataFrame:
        return cut(self.node, rows, columns).select(*columns, SK, (F.col("cnt") * sign).alias(M))

    def full(self, child: Annotated) -> Annotated:
        wide = child.widened()
        rows = consolidate(wide.df).withColumnRenamed(M, "cnt")
        return Annotated(self._emit(rows, wide.columns, 1), (), True)

    def capture(self, child: Annotated, version: int) -> Annotated:
        wide = child.widened()
        rows = consolidate(wide.df).withColumnRenamed(M, "cnt")
        self.state = AdditiveState(self.spark, [*wide.columns, SK], ["cnt"])
        self.state.add(version, self._kept(rows, wide.columns))
        self._read_head()
        return Annotated(self._rows(self._top(), wide.df.schema), (), True)

    def _kept(self, rows: DataFrame, columns: list[str]) -> DataFrame:
        if self.limit is None:
            return rows
        by = order_columns(self.node, columns)
        some = stored(rows.where("cnt > 0").orderBy(*by).limit(self.limit + 1), "top")
        found = some.orderBy(*by).collect()  # limit + 1 rows
        self.horizon = None
        if len(found) > self.limit:
            last = found[self.limit - 1]
            self.horizon = tuple(last[c] for c, _ in self.node.order)
            worse = found[self.limit]
            if tuple(worse[c] for c, _ in self.node.order) == self.horizon:  # a tie class is kept whole or not at all
                keep = [r for r in found[: self.limit] if tuple(r[c] for c, _ in self.node.order) != self.horizon]
                if len(keep) < self.node.k:
                    same = F.lit(True)
                    for c, v in zip((c for c, _ in self.node.order), self.horizon):
                        same = same & F.col(c).eqNullSafe(F.lit(v))
                    return rows.where("cnt > 0").where(same | self._within(self.horizon))
                self.horizon = tuple(keep[-1][c] for c, _ in self.node.order)
            return some.where(self._within(self.horizon))
        return some

    def _within(self, bound: tuple, order: list[tuple[str, bool]] | None = None) -> Column:
        """Not after the bound in the order."""
        out = F.lit(True)
        for (c, down), v in reversed(list(zip(order or self.node.order, bound))):
            if v is None:
                before, same = F.col(c).isNotNull(), F.col(c).isNull()
            else:
                before, same = F.coalesce(F.col(c) > F.lit(v) if down else F.col(c) < F.lit(v), F.lit(False)), F.coalesce(F.col(c) == F.lit(v), F.lit(False))
            out = before | (same & out)
        return out

    # ---- the head ----------------------------------------------------------------------------------------

    def _order(self) -> list[tuple[str, bool]]:
        """Every column of a row in the order of comparison, and whether it falls."""
        first = list(self.node.order)
        return [*first, *((c, False) for c in self.state.keys[:-1] if c not in dict(first)), (SK, False)]

    def _key(self) -> Callable:
        at = [(self.state.keys.index(c), down) for c, down in self._order()]

        def compare(a: tuple[tuple, int], b: tuple[tuple, int]) -> int:
            for i, down in at:
                if (found := _compared(a[0][i], b[0][i], down)) != 0:
                    return found
            return 0

        return cmp_to_key(compare)

    def _row(self, r: Row) -> tuple:
        return tuple(_held(r[c]) for c in self.state.keys)

    def _read_head(self) -> None:
        by = order_columns(self.node, self.state.keys[:-1])
        found = self.state.read().where("cnt > 0").orderBy(*by).limit(self.room + 1).collect()
        rows = [(self._row(r), r["cnt"]) for r in found]
        self.head = rows[: self.room]
        self.bound = self.head[-1][0] if len(rows) > self.room else None

    def _top(self) -> dict[tuple, int]:
        """The first k rows by multiplicity, the last one's reduced to fit."""
        out, left = {}, self.node.k
        for row, n in self.head:
            if left <= 0:
                break
            out[row] = min(n, left)
            left -= n
        return out

    def _rows(self, changes: dict[tuple, int], schema: StructType) -> DataFrame:
        kinds = {f.name: f for f in schema}
        named = StructType([*(kinds[c] for c in self.state.keys), kinds[M]])
        return self.spark.createDataFrame([(*row[:-1], list(row[-1]), n) for row, n in changes.items() if n], named)

    def maintain(self, delta: Annotated, version: int, recapture=None) -> Annotated:  # noqa: ANN001
        wide = delta.widened()
        if self.head is None:  # restored from the catalog
            self._read_head()
        before = self._top()
        rows = consolidate(wide.df).withColumnRenamed(M, "cnt")
        if self.horizon is not None:
            rows = rows.where(self._within(self.horizon))
        if len(self.state.parts) >= MOST_PARTS:
            self.state.compact()
        part = self.state.add(version, rows)
        order = self._order()
        if self.bound is not None:
            last = dict(zip(self.state.keys, self.bound))
            part = part.where(self._within(tuple(list(last[c]) if c == SK else last[c] for c, _ in order), order))
        # deletes here are of the head's rows; of the inserts no more can get into the head than it has room for
        most = len(self.head) + 2 * self.room
        near = part.orderBy(F.signum("cnt"), *order_columns(self.node, self.state.keys[:-1])).limit(most).collect()
        held = dict(self.head)
        for r in near:
            row = self._row(r)
            held[row] = held.get(row, 0) + r["cnt"]
            if held[row] < 0:
                raise ValueError("a row is deleted more often than it occurs")
        self.head = sorted(((row, n) for row, n in held.items() if n), key=self._key())
        if len(self.head) > 2 * self.room or len(near) == most:
            self.head = self.head[: self.room]
            self.bound = self.head[-1][0]
        if sum(n for _, n in self.head) < self.node.k and self.bound is not None:
            self.refilled += 1
            self._read_head()
        if sum(n for _, n in self.head) < self.node.k and self.horizon is not None:
            self.recaptured += 1
            self.capture(recapture(), version)
        after = self._top()
        return Annotated(self._rows({row: after.get(row, 0) - before.get(row, 0) for row in {**before, **after}}, wide.df.schema), (), True)

    def snapshot(self) -> tuple:
        return self.state.snapshot(), self.horizon, list(self.head) if self.head is not None else None, self.bound

    def restore(self, saved: tuple) -> None:
        self.state, self.horizon, self.head, self.bound = saved
