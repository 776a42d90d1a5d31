"""The experiment workloads over the given tables, and a generator for those that need their own."""

from __future__ import annotations

import random
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skipsketch.functions.ranges import Partitioning, RangeSet, equi_width_ranges
from skipsketch.plans.algebra import Aggregate, Distinct, Filter, Join, Node, Project, Scan, TopK
from skipsketch.session import Session, Strategy
from skipsketch.sources.delta import Database

LINEITEM = Scan("lineitem", ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_shipdate"))
ORDERS = Scan("orders", ("o_orderkey", "o_custkey", "o_totalprice", "o_orderdate"))
CUSTOMER = Scan("customer", ("c_custkey", "c_nationkey", "c_acctbal"))
NATION = Scan("nation", ("n_nationkey", "n_name"))
PART = Scan("part", ("p_partkey", "p_size"))
SUPPLIER = Scan("supplier", ("s_suppkey", "s_nationkey"))
EVENTS = Scan("events", ("event_id", "ts", "user_id", "event_type", "value"))
DOCUMENTS = Scan("documents", ("doc_id", "lang", "source"))

#: Expressions that are never negative in these tables.
POSITIVE = {"l_quantity", "l_extendedprice", "o_totalprice", "l_extendedprice * (1 - l_discount)", "value"}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{str(sf_dir).rstrip('/')}/{name}.parquet")


def key_ranges(spark: SparkSession, sf_dir: str, name: str, attr: str, p: int) -> RangeSet:
    """p equal ranges of a dense key; its maximum comes from the files' statistics."""
    top = (table(spark, sf_dir, name).agg(F.max(attr)).first()[0] or 0) + 1
    return equi_width_ranges(name, attr, 0, int(top), p) if top % p == 0 else RangeSet(name, attr, tuple(sorted({top * i // p for i in range(1, p)} - {0})))


def split_database(spark: SparkSession, sf_dir: str, names: dict[str, str], changed: set[str] | None = None, commit: bool = True) -> Database:
    """Tables at version 0 without the rows whose key is 0 by 40; version 1 inserts those and deletes the ones at 1.

    ``names`` gives each table's key column; tables outside ``changed`` stay whole.
    """
    changed = set(names) if changed is None else changed
    rows = {n: table(spark, sf_dir, n) for n in names}
    db = Database(spark, {n: df.where(f"{names[n]} % 40 <> 0") if n in changed else df for n, df in rows.items()})
    if commit:
        db.update({n: (rows[n].where(f"{names[n]} % 40 = 0"), rows[n].where(f"{names[n]} % 40 = 1")) for n in sorted(changed)})
    return db


# ---- plans -----------------------------------------------------------------------------------------------


def sum_having(c: float) -> Node:
    return Filter(Aggregate(LINEITEM, ("l_partkey",), (("qty", "sum", "l_quantity"),)), f"qty > {c}")


def count_having(c: int) -> Node:
    return Filter(Aggregate(LINEITEM, ("l_partkey",), (("n", "count", "*"),)), f"n > {c}")


def avg_interval(lo: float, hi: float) -> Node:
    return Filter(Aggregate(ORDERS, ("o_custkey",), (("price", "avg", "o_totalprice"),)), f"price > {lo} and price < {hi}")


def multi_aggregate(k: int, c: float = 60000) -> Node:
    """One average in the condition and k - 1 more that hold for every group."""
    args = ["l_extendedprice", "l_quantity", "l_discount", "l_tax", "l_extendedprice * l_discount", "l_quantity * l_tax", "l_extendedprice * l_tax", "l_quantity * l_discount", "l_extendedprice + l_quantity"]
    aggs = tuple((f"a{i}", "avg", args[i]) for i in range(k))
    return Filter(Aggregate(LINEITEM, ("l_partkey",), aggs), " and ".join([f"a0 > {c}", *(f"a{i} >= 0" for i in range(1, k))]))


def grouped(key: str, c: float) -> Node:
    """Average price by a key with few or many values."""
    child: Node = LINEITEM
    if key == "bucket":
        child = Project(LINEITEM, (("bucket", "l_partkey % 5000"), ("l_extendedprice", "l_extendedprice")))
    return Filter(Aggregate(child, (key,), (("price", "avg", "l_extendedprice"),)), f"price > {c}")


def join_having(c: float, share: int | None = None) -> Node:
    """Part joined with lineitem, average price by part; ``share`` keeps so many percent of the parts."""
    part: Node = PART if share is None else Filter(PART, f"p_partkey % 100 < {share}")
    return Filter(Aggregate(Join(part, LINEITEM, (("p_partkey", "l_partkey"),)), ("p_partkey",), (("price", "avg", "l_extendedprice"),)), f"price < {c}")


def one_to_many(kind: str, c: float) -> Node:
    """1-n joins of growing n: parts, suppliers, nations with lineitem."""
    if kind == "part":
        return join_having(c)
    supplied = Join(SUPPLIER, LINEITEM, (("s_suppkey", "l_suppkey"),))
    key = "s_suppkey" if kind == "supplier" else "s_nationkey"
    return Filter(Aggregate(Filter(supplied, "l_quantity >= 10"), (key,), (("price", "avg", "l_extendedprice"),)), f"price < {c}")


def many_to_many(users: int, c: int) -> Node:
    orders = Project(ORDERS, (("o_user", f"o_custkey % {users}"), ("o_totalprice", "o_totalprice")))
    return Filter(Aggregate(Join(orders, EVENTS, (("o_user", "user_id"),)), ("user_id",), (("n", "count", "*"),)), f"n > {c}")


def selective(limit: float, c: float) -> Node:
    return Filter(Aggregate(Filter(LINEITEM, f"l_quantity <= {limit}"), ("l_suppkey",), (("price", "avg", "l_extendedprice"),)), f"price > {c}")


def top_customers(k: int = 10) -> Node:
    return TopK(Aggregate(ORDERS, ("o_custkey",), (("price", "avg", "o_totalprice"),)), (("o_custkey", False),), k)


def top_spenders(k: int = 10) -> Node:
    return TopK(Aggregate(ORDERS, ("o_custkey",), (("total", "sum", "o_totalprice"),)), (("total", True),), k)


def returned_revenue(lo: str, hi: str, k: int = 20, descending: bool = False) -> Node:
    """Customers by revenue in a window of order dates, over four tables."""
    orders = Filter(ORDERS, f"o_orderdate >= timestamp_ntz '{lo} 00:00:00' and o_orderdate < timestamp_ntz '{hi} 00:00:00'")
    rows = Join(Join(Join(CUSTOMER, orders, (("c_custkey", "o_custkey"),)), LINEITEM, (("o_orderkey", "l_orderkey"),)), NATION, (("c_nationkey", "n_nationkey"),))
    total = Aggregate(rows, ("c_custkey", "n_name"), (("revenue", "sum", "l_extendedprice * (1 - l_discount)"),))
    return TopK(total, (("revenue", descending),), k)


def large_orders(c: int) -> Node:
    big = Filter(Aggregate(Project(LINEITEM, (("l_orderkey", "l_orderkey"), ("l_quantity", "l_quantity"))), ("l_orderkey",), (("qty", "sum", "l_quantity"),)), f"qty > {c}")
    return Join(big, Join(ORDERS, CUSTOMER, (("o_custkey", "c_custkey"),)), (("l_orderkey", "o_orderkey"),))


def part_volume(c: int) -> Node:
    """Parts of which much is ordered, with their size."""
    volume = Aggregate(Project(LINEITEM, (("l_partkey", "l_partkey"), ("l_quantity", "l_quantity"))), ("l_partkey",), (("qty", "sum", "l_quantity"),))
    return Join(Filter(volume, f"qty > {c}"), PART, (("l_partkey", "p_partkey"),))


def top_suppliers(lo: str, hi: str, k: int = 10) -> Node:
    """Suppliers by revenue shipped in a window."""
    rows = Filter(LINEITEM, f"l_shipdate >= timestamp_ntz '{lo} 00:00:00' and l_shipdate < timestamp_ntz '{hi} 00:00:00'")
    total = Aggregate(Join(SUPPLIER, rows, (("s_suppkey", "l_suppkey"),)), ("s_suppkey",), (("revenue", "sum", "l_extendedprice * (1 - l_discount)"),))
    return TopK(total, (("revenue", True),), k)


def as_view(plan: Node, ranges: RangeSet) -> Node:
    """What captures a sketch as a plain relational view: the ranges of the rows that join the qualifying groups.

    For classical view maintenance, which has no sketch type: the view is maintained like any query, a range is a
    column, and rows carry no annotations.  For a selection on groups of one table.
    """
    agg = plan.child if isinstance(plan, Filter) else plan
    if not isinstance(agg, Aggregate) or not isinstance(agg.child, Scan) or agg.child.table != ranges.table:
        raise ValueError("a condition on groups of one table")
    rows = Project(agg.child, (*((f"of_{k}", k) for k in agg.keys), ("frag", ranges.text(ranges.attr))))
    return Distinct(Project(Join(plan, rows, tuple((k, f"of_{k}") for k in agg.keys)), (("frag", "frag"),)))


def extreme(f: str) -> Node:
    return Aggregate(LINEITEM, ("l_suppkey",), (("price", f, "l_extendedprice"),))


def distinct_pairs() -> Node:
    return Distinct(Project(Filter(LINEITEM, "l_quantity >= 45"), (("l_partkey", "l_partkey"), ("l_suppkey", "l_suppkey"))))


def events_by_day(c: int = 5) -> Node:
    day = Project(EVENTS, (("user_id", "user_id"), ("day", "day(ts)"), ("event_id", "event_id")))
    return Filter(Aggregate(day, ("user_id", "day"), (("n", "count", "event_id"),)), f"n > {c}")


def events_four_keys(c: int = 5) -> Node:
    keys = Project(EVENTS, (("event_type", "event_type"), ("user_id", "user_id"), ("ten", "cast((day(ts) - 1) div 10 as int)"), ("half", "cast(hour(ts) div 12 as int)"), ("event_id", "event_id")))
    return Filter(Aggregate(keys, ("event_type", "user_id", "ten", "half"), (("n", "count", "event_id"),)), f"n > {c}")


def documents_by_source(c: int = 8) -> Node:
    return Filter(Aggregate(DOCUMENTS, ("lang", "source"), (("n", "count", "*"),)), f"n > {c}")


# ---- mixed workloads -------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Operation:
    kind: str  # query | update
    lo: float = 0
    hi: float = 0
    start: int = 0
    size: int = 0


def mixed(updates: int, queries: int, delta: int, n: int, keys: int, seed: int = 7) -> Iterator[Operation]:
    """n operations in the ratio updates to queries; updates take ``delta`` rows, queries vary their interval."""
    rng = random.Random(seed)
    start = 0
    for i in range(n):
        if i % (updates + queries) < updates:
            yield Operation("update", start=start % max(1, keys - delta), size=delta)
            start += delta
        else:
            lo = rng.uniform(171196, 300000)
            yield Operation("query", lo=round(lo, 2), hi=round(lo + rng.uniform(2000, 28000), 2))


def run_operations(session: Session, table: str, key: str, operations: list[Operation], plan: Callable[[float, float], Node]) -> list[dict]:
    """One row for each operation: seconds, cumulated seconds, size of the sketches; capture and maintenance included.

    An update takes rows out of the table, or puts them back when their turn comes again; which rows is looked
    up before the clock starts.
    """
    base, out, total, gone = session.db[table].base, [], 0.0, {}
    for i, o in enumerate(operations):
        at = (o.start, o.size)
        if o.kind == "update" and at not in gone:
            rows = [tuple(r) for r in base.where(F.col(key).between(o.start, o.start + o.size - 1)).collect()]
        began = time.perf_counter()
        if o.kind == "update":
            if at in gone:
                session.update_rows(table, inserts=gone.pop(at))
            else:
                gone[at] = rows
                session.update_rows(table, deletes=rows)
        else:
            session.query(plan(o.lo, o.hi)).write.format("noop").mode("overwrite").save()
        seconds = time.perf_counter() - began
        total += seconds
        out.append({"op_no": i, "kind": o.kind, "strategy": session.strategy.name, "delta_rows": o.size, "seconds": seconds, "cum_seconds": total, "sketch_frags": sum(len(s.fragments) for s in session.store.live.values()), "recaptured": session.counts["recaptured"]})
    return out


def run_mixed(spark: SparkSession, sf_dir: str, operations: list[Operation], strategy: Strategy, p: int = 100, backend: str = "auto") -> list[dict]:
    """The mixed workload on orders: averages by customer inside intervals that vary."""
    orders = table(spark, sf_dir, "orders").select(*ORDERS.columns)
    session = Session(spark, {"orders": orders}, {"orders": key_ranges(spark, sf_dir, "orders", "o_custkey", p)}, strategy, positive=POSITIVE, backend=backend)
    return run_operations(session, "orders", "o_orderkey", operations, avg_interval)


def run_synthetic(spark: SparkSession, path: str, operations: list[Operation], strategy: Strategy, groups: int, p: int = 1000) -> list[dict]:
    """The same on a generated table, written sorted by its group key so that files' statistics can skip."""
    rows = spark.read.parquet(path)
    session = Session(spark, {"t": rows}, {"t": equi_width_ranges("t", "a", 0, groups, p)}, strategy, backend="auto")
    scan = Scan("t", tuple(rows.columns))
    return run_operations(session, "t", "id", operations, lambda lo, hi: Filter(Aggregate(scan, ("a",), (("v", "avg", "b0"),)), f"v > {lo} and v < {hi}"))


def write_synthetic(spark: SparkSession, path: str, rows: int, groups: int, files: int = 40) -> None:
    synth_table(spark, rows, groups).repartitionByRange(files, "a").sortWithinPartitions("a").write.mode("overwrite").parquet(path)


# ---- generator -------------------------------------------------------------------------------------------


def synth_table(spark: SparkSession, rows: int, groups: int, attributes: int = 11, seed: int = 1) -> DataFrame:
    """A key, one uniform attribute ``a`` with so many values, and others linear in it with Gaussian noise."""
    base = spark.range(rows).select("id", F.floor(F.rand(seed) * groups).cast("long").alias("a"))
    return base.select("id", "a", *(F.round(F.col("a") * (i + 1) + F.randn(seed + i + 1) * groups / 10, 2).alias(f"b{i}") for i in range(attributes - 1)))


def join_helper(spark: SparkSession, keys: int, each: int) -> DataFrame:
    """A table in which each of so many keys stands ``each`` times."""
    return spark.range(keys * each).select((F.col("id") % keys).alias("k"), F.col("id").alias("payload"))


def partitioning(*ranges: RangeSet) -> Partitioning:
    return Partitioning(*ranges)
