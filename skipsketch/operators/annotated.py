"""Sketch-annotated signed rows and the operators on them that need no state.

Below any aggregation a row lies in one fragment of each sketched table instance, so its sketch is one int
column for each instance (``thin``).  Above, it is a sorted array of global fragment ids (``__sk``).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skipsketch.functions.ranges import Partitioning
from skipsketch.plans.algebra import Filter, Join, M, Node, Project, Scan, UnionAll

SK = "__sk"


@dataclass(frozen=True)
class Annotated:
    df: DataFrame
    thin: tuple[str, ...] = ()
    wide: bool = False

    @property
    def columns(self) -> list[str]:
        return [c for c in self.df.columns if c not in self.thin and c not in (SK, M)]

    def sketch(self) -> Column:
        """The row's sketch as an array of global ids."""
        own = F.array(*self.thin) if self.thin else F.array().cast("array<int>")
        if self.wide:
            own = F.array_union(own, SK) if self.thin else F.col(SK)
        return F.array_sort(F.array_distinct(own))

    def widened(self) -> Annotated:
        if self.wide and not self.thin:
            return self
        return Annotated(self.df.select(*self.columns, self.sketch().alias(SK), M), (), True)

    def empty(self) -> Annotated:
        return replace(self, df=self.df.limit(0))


def scan(node: Scan, rows: DataFrame, phi: Partitioning) -> Annotated:
    cols = [F.col(c).alias(node.prefix + c) for c in node.columns]
    if node.table not in phi:
        return Annotated(rows.select(*cols, M))
    ranges = phi.ranges[node.table]
    name = f"__f_{node.prefix}{node.table}"
    frag = (ranges.column(ranges.attr) + F.lit(phi.offset[node.table])).cast("int").alias(name)
    return Annotated(rows.select(*cols, frag, M), (name,))


def keep(child: Annotated, condition: str) -> Annotated:
    return replace(child, df=child.df.where(F.expr(condition)))


def project(child: Annotated, exprs: tuple[tuple[str, str], ...]) -> Annotated:
    extra = [*child.thin, *([SK] if child.wide else []), M]
    return replace(child, df=child.df.select(*(F.expr(e).alias(n) for n, e in exprs), *extra))


def join(left: Annotated, right: Annotated, node: Join, sign: int = 1, small: str = "") -> Annotated:
    """Signed join: multiplicities multiply, sketches unite.  ``small`` names a side to broadcast, whose rows were counted."""
    a, b = left.df.withColumnRenamed(M, "__ml"), right.df.withColumnRenamed(M, "__mr")
    if left.wide and right.wide:
        b = b.withColumnRenamed(SK, "__skr")
    a, b = (F.broadcast(a) if small == "left" else a), (F.broadcast(b) if small == "right" else b)
    on = None
    for x, y in node.on:
        on = F.col(x) == F.col(y) if on is None else on & (F.col(x) == F.col(y))
    if node.condition:
        on = F.expr(node.condition) if on is None else on & F.expr(node.condition)
    both = a.join(b, on, "inner") if on is not None else a.crossJoin(b)
    thin = left.thin + right.thin
    sk = [F.array_sort(F.array_union(SK, "__skr")).alias(SK)] if left.wide and right.wide else [SK] if left.wide or right.wide else []
    out = both.select(*left.columns, *right.columns, *thin, *sk, (F.col("__ml") * F.col("__mr") * sign).alias(M))
    return Annotated(out, thin, left.wide or right.wide)


def union(*parts: Annotated) -> Annotated:
    first = parts[0]
    if any((p.thin, p.wide) != (first.thin, first.wide) for p in parts):
        parts = tuple(p.widened() for p in parts)
    df = parts[0].df
    for p in parts[1:]:
        df = df.unionByName(p.df)
    return replace(parts[0], df=df)


def stateless(node: Node, run: Callable[[Node], Annotated]) -> Annotated | None:
    """Selection, projection and bag union, the same on tables and on deltas."""
    if isinstance(node, Filter):
        return keep(run(node.child), node.condition)
    if isinstance(node, Project):
        return project(run(node.child), node.exprs)
    if isinstance(node, UnionAll):
        left, right = run(node.left), run(node.right)
        return union(left, replace(right, df=right.df))
    return None
