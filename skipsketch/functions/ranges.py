"""Range partitions of a table's attribute, and the fragment of a value.

A partition covers the whole domain: the first and the last range are unbounded.  Ranges are half-open; NULL
belongs to no range and has a fragment of its own, the one after the last; NaN sorts last, as in Spark.
"""

from __future__ import annotations

import bisect
import math
from dataclasses import dataclass
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skipsketch.shipping import ship

#: Up to so many ranges a decision tree of expressions stays within one compiled method.
TREE = 256


@dataclass(frozen=True)
class RangeSet:
    """``cuts`` are the inner bounds, ascending: fragment i holds cuts[i - 1] <= value < cuts[i]."""

    table: str
    attr: str
    cuts: tuple

    @property
    def count(self) -> int:
        """Number of fragments without that of NULL."""
        return len(self.cuts) + 1

    @property
    def null_fragment(self) -> int:
        return self.count

    @property
    def size(self) -> int:
        return self.count + 1

    def fragment_of(self, value: Any) -> int:
        if value is None:
            return self.null_fragment
        if isinstance(value, float) and math.isnan(value):
            return self.count - 1
        return bisect.bisect_right(self.cuts, value)

    def column(self, col: Column | str) -> Column:
        """The fragment of a column, as int."""
        name = f"`{col}`" if isinstance(col, str) else ""
        col = F.col(col) if isinstance(col, str) else col
        if not self.cuts:
            return F.when(col.isNull(), F.lit(1)).otherwise(F.lit(0))
        if self.count <= TREE and name and all(type(c) in (int, float) and c - c == 0 for c in self.cuts):
            return F.expr(self.text(name.strip("`")))
        if self.count <= TREE:
            return F.when(col.isNull(), F.lit(self.null_fragment)).otherwise(_tree(col, self.cuts, 0, len(self.cuts)))
        found = _searched(self.cuts)(F.coalesce(col, F.lit(self.cuts[0])))  # no nulls in pandas, where they would be NaN
        return F.when(col.isNull(), F.lit(self.null_fragment)).otherwise(found)

    def text(self, attr: str) -> str:
        """The fragment as SQL, for few ranges of numbers."""
        return f"CASE WHEN `{attr}` IS NULL THEN {self.null_fragment} ELSE {_tree_text(f'`{attr}`', self.cuts, 0, len(self.cuts))} END"

    def predicate(self, fragments: set[int], attr: str | None = None) -> Column:
        """The condition that a row lies in one of the fragments; adjacent ones are merged, so it can be pushed down."""
        name = attr or self.attr
        if all(type(c) in (int, float) and c - c == 0 for c in self.cuts):
            return F.expr(self._text(fragments, f"`{name}`"))  # one call to the JVM, however many runs
        col = F.col(name)
        out = None
        for lo, hi in self.runs(fragments):
            low, high = self.bounds(lo)[0], self.bounds(hi)[1]
            c = col.isNotNull() if low is None and high is None else None
            if low is not None:
                c = col >= F.lit(low)
            if high is not None:
                c = col < F.lit(high) if c is None else c & (col < F.lit(high))
            out = c if out is None else out | c
        if self.null_fragment in fragments:
            out = col.isNull() if out is None else out | col.isNull()
        return F.lit(False) if out is None else out

    def _text(self, fragments: set[int], name: str) -> str:
        parts = []
        for lo, hi in self.runs(fragments):
            low, high = self.bounds(lo)[0], self.bounds(hi)[1]
            both = [f"{name} >= {_number(low)}"] if low is not None else []
            both += [f"{name} < {_number(high)}"] if high is not None else []
            parts.append(f"({' and '.join(both)})" if both else f"{name} is not null")
        if self.null_fragment in fragments:
            parts.append(f"{name} is null")
        return " or ".join(parts) or "false"

    def bounds(self, fragment: int) -> tuple[Any, Any]:
        """Lower (inclusive) and upper (exclusive) bound; None where unbounded."""
        return (self.cuts[fragment - 1] if fragment > 0 else None, self.cuts[fragment] if fragment < len(self.cuts) else None)

    def runs(self, fragments: set[int]) -> list[tuple[int, int]]:
        """Maximal runs of adjacent fragments, NULL's left out."""
        out: list[tuple[int, int]] = []
        for f in sorted(x for x in fragments if x < self.count):
            if out and out[-1][1] == f - 1:
                out[-1] = (out[-1][0], f)
            else:
                out.append((f, f))
        return out


@dataclass(frozen=True)
class GridRanges:
    """Ranges over several attributes of one table; a fragment is a cell, numbered in mixed radix."""

    table: str
    parts: tuple[RangeSet, ...]

    @property
    def attr(self) -> str:
        return self.parts[0].attr

    @property
    def size(self) -> int:
        return math.prod(p.size for p in self.parts)

    def column(self, col: Any = None) -> Column:
        out = None
        for p in self.parts:
            one = p.column(p.attr)
            out = one if out is None else out * p.size + one
        return out

    def cell(self, fragment: int) -> tuple[int, ...]:
        out = []
        for p in reversed(self.parts):
            fragment, i = divmod(fragment, p.size)
            out.append(i)
        return tuple(reversed(out))

    def predicate(self, fragments: set[int], attr: str | None = None) -> Column:
        """For each run of cells along the last attribute, one box."""
        by: dict[tuple[int, ...], set[int]] = {}
        for f in fragments:
            *head, last = self.cell(f)
            by.setdefault(tuple(head), set()).add(last)
        out = None
        for head, lasts in sorted(by.items()):
            c = self.parts[-1].predicate(lasts)
            for p, i in zip(self.parts, head):
                c = p.predicate({i}) & c
            out = c if out is None else out | c
        return F.lit(False) if out is None else out


def _tree(col: Column, cuts: tuple, lo: int, hi: int) -> Column:
    """Fragments lo..hi by halving: a comparison for each level, not for each range."""
    if lo == hi:
        return F.lit(lo)
    mid = (lo + hi) // 2
    return F.when(col < F.lit(cuts[mid]), _tree(col, cuts, lo, mid)).otherwise(_tree(col, cuts, mid + 1, hi))


def _number(x: float) -> str:
    return f"{x!r}D" if isinstance(x, float) else f"{x}L"


def _tree_text(name: str, cuts: tuple, lo: int, hi: int) -> str:
    """The same as SQL, which is parsed at once instead of built call by call."""
    if lo == hi:
        return str(lo)
    mid = (lo + hi) // 2
    return f"CASE WHEN {name} < {_number(cuts[mid])} THEN {_tree_text(name, cuts, lo, mid)} ELSE {_tree_text(name, cuts, mid + 1, hi)} END"


def _searched(cuts: tuple):  # noqa: ANN202
    from pyspark.sql import SparkSession

    if (spark := SparkSession.getActiveSession()) is not None:
        ship(spark)
    bounds = np.array(cuts, dtype=object if isinstance(cuts[0], str) else None)

    @F.pandas_udf("int")
    def fragment(values: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(bounds, values.to_numpy().astype(bounds.dtype), "right").astype(np.int32))

    return fragment


def ranges_from_bounds(table: str, attr: str, cuts: list) -> RangeSet:
    return RangeSet(table, attr, tuple(sorted(set(cuts))))


def trivial_range(table: str, attr: str) -> RangeSet:
    """One range that covers everything."""
    return RangeSet(table, attr, ())


def equi_width_ranges(table: str, attr: str, low: float, high: float, p: int) -> RangeSet:
    whole = isinstance(low, int) and isinstance(high, int) and (high - low) % p == 0
    return ranges_from_bounds(table, attr, [low + (high - low) * i // p if whole else low + (high - low) * i / p for i in range(1, p)])


def equi_depth_ranges(df: DataFrame, table: str, attr: str, p: int, exact: bool = False) -> RangeSet:
    """Bounds at the p-quantiles of the attribute; equal bounds collapse, so fewer ranges may result."""
    share = [i / p for i in range(1, p)]
    if not share:
        return trivial_range(table, attr)
    if exact:
        rows = df.select(*(F.expr(f"percentile_disc({s}) WITHIN GROUP (ORDER BY `{attr}`)").alias(f"q{i}") for i, s in enumerate(share))).first()
        found = list(rows)
    else:
        found = df.agg(F.percentile_approx(attr, share, max(10_000, 20 * p)).alias("q")).first()["q"] or []
    return ranges_from_bounds(table, attr, [x for x in found if x is not None])


def grid_ranges(table: str, parts: list[RangeSet]) -> GridRanges:
    return GridRanges(table, tuple(parts))


#: Runs of adjacent ranges up to which a filter names each run.
MOST_RUNS = 64


def restrict(df: DataFrame, ranges: RangeSet | GridRanges, fragments: set[int]) -> DataFrame:
    """The rows in the fragments.

    Few runs become one pushed-down condition.  Of many, the files see the envelope of all runs, and the rows
    inside it are looked up and joined with the list of fragments, which has at most as many rows as there are ranges.
    """
    if isinstance(ranges, GridRanges) or len(ranges.runs(fragments)) <= MOST_RUNS:
        return df.where(ranges.predicate(fragments))
    runs = ranges.runs(fragments)
    whole = set(range(runs[0][0], runs[-1][1] + 1)) | (fragments & {ranges.null_fragment})
    wanted = df.sparkSession.createDataFrame([(f,) for f in sorted(fragments)], "__frag int")
    inside = annotate(df.where(ranges.predicate(whole)), ranges)
    return inside.join(F.broadcast(wanted), "__frag", "left_semi").drop("__frag")


def split_range(ranges: RangeSet, fragment: int, at: Any) -> tuple[RangeSet, dict[int, set[int]]]:
    """The ranges with one split, and which new fragments each old one becomes."""
    new = ranges_from_bounds(ranges.table, ranges.attr, [*ranges.cuts, at])
    if new.fragment_of(at) != fragment + 1:
        raise ValueError("the new bound lies outside the range")
    return new, {i: {i} if i < fragment else {i, i + 1} if i == fragment else {i + 1} for i in range(ranges.size)}


def merge_ranges(ranges: RangeSet, fragment: int) -> tuple[RangeSet, dict[int, set[int]]]:
    """The ranges with ``fragment`` and the next one as one, and the new fragment of each old one."""
    new = RangeSet(ranges.table, ranges.attr, ranges.cuts[:fragment] + ranges.cuts[fragment + 1 :])
    return new, {i: {i if i <= fragment else i - 1} for i in range(ranges.size)}


def remap(fragments: set[int], moves: dict[int, set[int]]) -> set[int]:
    """A sketch over changed ranges; both halves of a split range stay in it, which is sound."""
    return set().union(*(moves[f] for f in fragments)) if fragments else set()


class Partitioning:
    """Ranges of the sketched tables of a query; fragments of different tables have different global ids."""

    def __init__(self, *ranges: RangeSet | GridRanges):
        self.ranges = {r.table: r for r in ranges}
        self.offset, at = {}, 0
        for r in ranges:
            self.offset[r.table] = at
            at += r.size
        self.size = at

    def __contains__(self, table: str) -> bool:
        return table in self.ranges

    def local(self, fragment: int) -> tuple[str, int]:
        for t, r in self.ranges.items():
            if self.offset[t] <= fragment < self.offset[t] + r.size:
                return t, fragment - self.offset[t]
        raise KeyError(fragment)

    def split(self, fragments: set[int]) -> dict[str, set[int]]:
        out: dict[str, set[int]] = {t: set() for t in self.ranges}
        for f in fragments:
            t, i = self.local(f)
            out[t].add(i)
        return out


def annotate(df: DataFrame, ranges: RangeSet | GridRanges, name: str = "__frag") -> DataFrame:
    """Every row with its fragment; narrow."""
    return df.withColumn(name, ranges.column(ranges.attr))


def sketch_of(df: DataFrame, ranges: RangeSet | GridRanges) -> DataFrame:
    """bucket, bitmap: the fragments that hold a row, as a bitmap aggregated by Spark (a row for each 32,768 fragments)."""
    frag = annotate(df, ranges).select(F.col("__frag").cast("long").alias("f"))
    return frag.groupBy(F.bitmap_bucket_number("f").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("f")).alias("bitmap"))


def fragments_in(rows: list) -> set[int]:
    """The fragments in collected rows of ``sketch_of``."""
    out = set()
    for r in rows:
        bits = np.unpackbits(np.frombuffer(bytes(r["bitmap"]), np.uint8), bitorder="little")
        base = (r["bucket"] - 1) * 32768
        out |= {int(base + i + 1) for i in np.flatnonzero(bits)} if r["bucket"] > 0 else {int(i) for i in np.flatnonzero(bits)}
    return out


def sketch_bytes(p: int) -> int:
    """Size of a sketch over p ranges as a bit vector with its header."""
    return 8 * -(-p // 64) + 24


def ranges_bytes(p: int) -> int:
    """Size of a list of p ranges, p + 1 bounds."""
    return 44 * p + 108
