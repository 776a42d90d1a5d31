"""A plan by Spark's own operators over plain tables: the query as it is, without signed rows, decimals or sketches.

The reference for answers, and the baseline for what a query costs without this package.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skipsketch.operators.topk import order_columns
from skipsketch.plans.algebra import Aggregate, Distinct, Filter, Join, Node, Project, Scan, TopK, UnionAll, UnsupportedForMaintenance


def plain(tables: dict[str, DataFrame], node: Node) -> DataFrame:
    def run(n: Node) -> DataFrame:
        if isinstance(n, Scan):
            return tables[n.table].select(*(F.col(c).alias(n.prefix + c) for c in n.columns))
        if isinstance(n, Filter):
            return run(n.child).where(F.expr(n.condition))
        if isinstance(n, Project):
            return run(n.child).select(*(F.expr(e).alias(name) for name, e in n.exprs))
        if isinstance(n, Join):
            left, right = run(n.left), run(n.right)
            on = None
            for a, b in n.on:
                on = F.col(a) == F.col(b) if on is None else on & (F.col(a) == F.col(b))
            if n.condition:
                on = F.expr(n.condition) if on is None else on & F.expr(n.condition)
            return left.join(right, on) if on is not None else left.crossJoin(right)
        if isinstance(n, Aggregate):
            child = run(n.child)
            aggs = [F.expr(f"{f}({e})").alias(name) for name, f, e in n.aggs]
            if n.keys:
                return child.groupBy(*n.keys).agg(*aggs) if aggs else child.select(*n.keys).distinct()
            some = child.agg(F.count("*").alias("__n"), *aggs)  # over no rows there is no result row
            return some.where("__n > 0").drop("__n")
        if isinstance(n, Distinct):
            return run(n.child).distinct()
        if isinstance(n, TopK):
            child = run(n.child)
            return child.orderBy(*order_columns(n, child.columns, False)).limit(n.k)
        if isinstance(n, UnionAll):
            return run(n.left).unionByName(run(n.right))
        raise UnsupportedForMaintenance(type(n).__name__)

    return run(node)
