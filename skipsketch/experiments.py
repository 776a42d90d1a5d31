"""The timed experiments, one JSON line for each figure.

``python -m skipsketch.experiments NAME ... [--dir TABLES] [--operations N]`` runs mix, topk, eager, granularity, selective,
groups, joins, pushdown, bloom, tpch, memory, break_even, or all of them.  Deltas stand on the driver and
in the log alike; capture and maintenance are in the times where the workload says so.
"""

from __future__ import annotations

import argparse
import json
import random
import time
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skipsketch import workloads as w
from skipsketch.functions.ranges import Partitioning, RangeSet, equi_width_ranges
from skipsketch.metrics import break_even, speedup, state_bytes, timed
from skipsketch.operators.maintain import Options, capture, maintain, recapture_fragments
from skipsketch.operators.memory import MemorySketch
from skipsketch.plans.algebra import Aggregate, Filter, Join, Node, Scan
from skipsketch.queries import BOTH, dense
from skipsketch.session import EagerStrategy, FullMaintenance, LazyStrategy, NoSketch, Session
from skipsketch.sources.delta import Database

REALISTIC = (10, 50, 100, 500, 1000)
Row = dict


def mix(spark: SparkSession, d: str, operations: int = 1000, ratios: tuple = ((1, 5), (1, 1), (5, 1)), deltas: tuple = (1, 20, 200, 2000)) -> Iterator[Row]:
    """Mixed workload: cumulated seconds of each strategy, capture and maintenance included."""
    keys = w.table(spark, d, "orders").agg(F.max("o_orderkey")).first()[0] + 1
    for updates, queries in ratios:
        for delta in deltas:
            for strategy in (LazyStrategy(), EagerStrategy(50), FullMaintenance(), NoSketch()):
                rows = w.run_mixed(spark, d, list(w.mixed(updates, queries, delta, operations, keys)), strategy)
                yield {"experiment": "mix", "ratio": f"{updates}U{queries}Q", "delta": delta, "strategy": strategy.name, "operations": operations, "seconds": rows[-1]["cum_seconds"]}


def topk(spark: SparkSession, d: str, limits: tuple = (20, 50, 100, None), updates: int = 500, each: int = 20) -> Iterator[Row]:
    """Deletes under a bounded top-k: seconds, recaptures and state by kind of deletes and rows kept; None is all, in memory."""
    orders = w.table(spark, d, "orders").select(*w.ORDERS.columns)
    rows = [tuple(r) for r in orders.orderBy("o_custkey", "o_orderkey").limit(50_000).collect()]
    for kind in ("minimal", "random", "mix2", "mix4"):
        for limit in limits:
            db = Database(spark, {"orders": spark.createDataFrame(rows, orders.schema)})
            phi = Partitioning(dense(spark, d, "orders", "o_custkey"))
            sketch = MemorySketch(db, w.top_customers(), phi) if limit is None else capture(db, w.top_customers(), phi, options=Options(limit=limit))
            rng, left, seconds, done = random.Random(5), list(rows), 0.0, 0
            for i in range(updates):
                lowest = kind == "minimal" or kind == "mix2" and i % 3 == 2 or kind == "mix4" and i % 5 == 4
                first = sorted({r[1] for r in left[: 20 * each]})[:2]
                gone = [r for r in left[: 20 * each] if r[1] in first] if lowest else rng.sample(left, min(each, len(left)))
                if not gone:
                    break
                drop = set(gone)
                left = [r for r in left if r not in drop]
                db.version += 1
                began = time.perf_counter()
                db["orders"].commit_rows(db.version, [], gone)
                sketch.maintain() if limit is None else maintain(db, sketch)
                seconds += time.perf_counter() - began
                done += 1
            memory = limit is None
            yield {"experiment": "topk", "deletes": kind, "limit": "all, in memory" if memory else limit, "updates": done, "seconds": seconds, "recaptured": 0 if memory else sketch.measures.recaptured, "state_bytes": sketch.state_bytes() if memory else state_bytes(sketch)}


def eager_cost(spark: SparkSession, d: str, batches: tuple = (1, 5, 10, 20, 50, 100, 200, 500, 1000, 0), updates: int = 1000, join: bool = False) -> Iterator[Row]:
    """Seconds of so many updates of ten rows by batch size; 0 is lazy, with one query at the end."""
    name, key = ("lineitem", "l_orderkey") if join else ("orders", "o_orderkey")
    plan = w.join_having(50000, 5) if join else w.avg_interval(345000, 355000)
    tables = {t: w.table(spark, d, t) for t in plan.tables()}
    columns = next(s for s in plan.scans() if s.table == name).columns
    tables[name] = tables[name].select(*columns)
    gone = [tuple(r) for r in tables[name].orderBy(key).limit(10 * updates).collect()]
    ranges = {t: dense(spark, d, t, a) for t, a, _ in BOTH} if join else {"orders": dense(spark, d, "orders", "o_custkey")}
    for batch in batches:
        s = Session(spark, tables, ranges, EagerStrategy(batch) if batch else LazyStrategy(), positive=w.POSITIVE, backend="auto")
        s.query(plan).count()
        began = time.perf_counter()
        for i in range(0, len(gone), 10):
            s.update_rows(name, deletes=gone[i : i + 10])
        if not batch:
            s.query(plan).count()
        yield {"experiment": "eager_join" if join else "eager", "batch": batch, "updates": updates, "seconds": time.perf_counter() - began, "maintained": s.counts["maintained"]}


def swept(spark: SparkSession, tables: dict[str, DataFrame], plan: Node, phi: Partitioning, name: str, key: str, deltas: tuple = REALISTIC, repeats: int = 10, options: Options | None = None) -> Iterator[Row]:
    """Median seconds of maintenance on both backends by delta size, deletes and inserts in turn, against a new capture."""
    columns = next(s for s in plan.scans() if s.table == name).columns
    tables = dict(tables)
    tables[name] = tables[name].select(*columns)
    held = tables[name].where(f"{key} % 7 = 3").limit(max(deltas)).collect()
    tables[name] = tables[name].where(f"{key} % 7 <> 3")
    full = timed(lambda: recapture_fragments(Database(spark, tables), plan, phi), repeats)
    for backend in ("memory", "tables"):
        db = Database(spark, tables)
        try:
            sketch = MemorySketch(db, plan, phi) if backend == "memory" else capture(db, plan, phi, options=options)
        except ValueError:
            continue
        for n in deltas:
            rows, turn = [tuple(r) for r in held[:n]], [0]

            def work() -> None:
                out = turn[0] % 2
                turn[0] += 1
                db.version += 1
                db[name].commit_rows(db.version, [] if out else rows, rows if out else [])
                sketch.maintain() if backend == "memory" else maintain(db, sketch)

            found = timed(work, repeats + repeats % 2)
            yield {"backend": backend, "delta": n, **found, "full": full["median"], "speedup": speedup(full["median"], found["median"])}


def _with(experiment: str, rows: Iterator[Row], **more) -> Iterator[Row]:  # noqa: ANN003
    for r in rows:
        yield {"experiment": experiment, **more, **r}


def granularity(spark: SparkSession, d: str, counts: tuple = (10, 50, 100, 500, 1000, 5000)) -> Iterator[Row]:
    tables = {t: w.table(spark, d, t) for t in ("part", "lineitem")}
    for p in counts:
        phi = Partitioning(*(RangeSet(t, a, w.key_ranges(spark, d, "part", "p_partkey", p).cuts) for t, a, _ in BOTH))
        yield from _with("granularity", swept(spark, tables, w.join_having(46000), phi, "lineitem", "l_orderkey", (100, 1000)), ranges=p)


def selective(spark: SparkSession, d: str) -> Iterator[Row]:
    tables = {t: w.table(spark, d, t) for t in ("part", "lineitem")}
    for share in (1, 5, 10):
        phi = Partitioning(*(dense(spark, d, *r) for r in BOTH))
        for bloom in (False, True):
            yield from _with("selective", swept(spark, tables, w.join_having(50000, share), phi, "lineitem", "l_orderkey", options=Options(bloom=bloom)), share=share, bloom=bloom)


def bloom(spark: SparkSession, d: str) -> Iterator[Row]:
    """Large deltas with and without the filter."""
    for share in (1, 5, 10):
        for on in (False, True):
            db = w.split_database(spark, d, {"lineitem": "l_orderkey", "part": "p_partkey"}, {"lineitem"}, commit=False)
            sketch = capture(db, w.join_having(50000, share), Partitioning(*(dense(spark, d, *r) for r in BOTH)), options=Options(bloom=on))
            rows = w.table(spark, d, "lineitem")
            db.update({"lineitem": (rows.where("l_orderkey % 40 = 0"), rows.where("l_orderkey % 40 = 1"))})
            began = time.perf_counter()
            maintain(db, sketch)
            yield {"experiment": "bloom", "share": share, "bloom": on, "seconds": time.perf_counter() - began, "delta_rows": sketch.measures.delta_rows, "joined": sketch.measures.joined if on else sketch.measures.delta_rows}


def groups(spark: SparkSession, d: str, rows: int = 10_000_000, counts: tuple = (50, 1000, 5000, 500_000)) -> Iterator[Row]:
    """Number of groups, on generated tables."""
    for n in counts:
        table = w.synth_table(spark, rows, n, 3).cache()
        plan = Filter(Aggregate(Scan("t", ("id", "a", "b0")), ("a",), (("v", "avg", "b0"),)), f"v > {0.9 * n}")
        yield from _with("groups", swept(spark, {"t": table}, plan, Partitioning(equi_width_ranges("t", "a", 0, n, 50)), "t", "id"), groups=n)
        table.unpersist()


def joins(spark: SparkSession, d: str, rows: int = 1_000_000, one: tuple = (20, 2000, 20_000, 200_000), many: tuple = ((20, 2000), (50, 2000))) -> Iterator[Row]:
    """1-n and m-n joins of generated tables; ``rows`` on the larger side."""
    for m, n in [*((1, n) for n in one), *many]:
        keys = max(1, rows // n)
        left = w.join_helper(spark, keys, m).select(F.col("k").alias("lk"), F.col("payload").alias("lp")).cache()
        right = w.join_helper(spark, keys, n).cache()
        plan = Filter(Aggregate(Join(Scan("l", ("lk", "lp")), Scan("r", ("k", "payload")), (("lk", "k"),)), ("lk",), (("s", "avg", "payload"),)), f"s < {rows // 2}")
        phi = Partitioning(RangeSet("l", "lk", tuple(range(max(1, keys // 50), keys, max(1, keys // 50)))))
        yield from _with("joins", swept(spark, {"l": left, "r": right}, plan, phi, "r", "payload", (10, 100, 1000), 4), m=m, n=n)
        left.unpersist()
        right.unpersist()


def pushdown(spark: SparkSession, d: str) -> Iterator[Row]:
    """Seconds and fetched rows with and without the selection in the delta's fetch; the delta is 2.5 % of the table."""
    rows = w.table(spark, d, "lineitem")
    for share in (2, 25, 50, 75, 100):
        plan = w.selective(share * 0.5, 50000)
        for on in (False, True):
            db = w.split_database(spark, d, {"lineitem": "l_orderkey"}, commit=False)
            sketch = capture(db, plan, Partitioning(dense(spark, d, "lineitem", "l_suppkey")), options=Options(pushdown=on))
            db.update({"lineitem": (rows.where("l_orderkey % 40 = 0"), None)})
            began = time.perf_counter()
            maintain(db, sketch)
            yield {"experiment": "pushdown", "share": share, "pushed": on, "seconds": time.perf_counter() - began}


def tpch(spark: SparkSession, d: str) -> Iterator[Row]:
    loads = {
        "returned_revenue": (w.returned_revenue("1995-01-01", "1995-04-01", descending=True), [("customer", "c_custkey", 100)]),
        "large_orders": (w.large_orders(250), [("orders", "o_custkey", 100), ("lineitem", "l_orderkey", 100)]),
        "part_volume": (w.part_volume(1100), BOTH),
        "top_suppliers": (w.top_suppliers("1995-03-01", "1995-06-01"), [("supplier", "s_suppkey", 100), ("lineitem", "l_suppkey", 100)]),
    }
    for name, (plan, ranges) in loads.items():
        tables = {t: w.table(spark, d, t) for t in plan.tables()}
        yield from _with("tpch", swept(spark, tables, plan, Partitioning(*(dense(spark, d, *r) for r in ranges)), "lineitem", "l_orderkey"), query=name)


def memory(spark: SparkSession, d: str) -> Iterator[Row]:
    """Bytes of operator state, on tables and in memory."""
    loads = {**{f"groups_{k}": (w.grouped(k, 50000), [("lineitem", k, 100)]) for k in ("l_suppkey", "l_orderkey")}, **{f"selective_{s}": (w.join_having(50000, s), BOTH) for s in (1, 5, 10)}}
    for name, (plan, ranges) in loads.items():
        db = Database(spark, {t: w.table(spark, d, t) for t in plan.tables()})
        phi = Partitioning(*(dense(spark, d, *r) for r in ranges))
        yield {"experiment": "memory", "query": name, "tables_bytes": state_bytes(capture(db, plan, phi)), "memory_bytes": MemorySketch(db, plan, phi).state_bytes()}
    for limit in (1000, 5000, 10_000, 20_000, None):
        plan = w.returned_revenue("1995-01-01", "1995-04-01", descending=True)
        db = Database(spark, {t: w.table(spark, d, t) for t in plan.tables()})
        sketch = capture(db, plan, Partitioning(dense(spark, d, "customer", "c_custkey")), options=Options(limit=limit))
        yield {"experiment": "memory", "query": "returned_revenue", "limit": limit, "tables_bytes": state_bytes(sketch)}


def even(spark: SparkSession, d: str, plan: Node, phi: Partitioning, name: str, key: str, steps: int = 6, largest: float = 0.5) -> float:
    """The share of a table from which a new capture is faster than maintenance on state tables, by bisection."""
    tables = {t: w.table(spark, d, t) for t in plan.tables()}

    def times(share: float) -> tuple[float, float]:
        n = max(1, round(1000 * share))
        rows = tables[name].where(F.pmod(F.xxhash64(key), F.lit(1000)) < n)
        db = Database(spark, tables)
        sketch = capture(db, plan, phi)
        db.update({name: (None, rows)})
        began = time.perf_counter()
        maintain(db, sketch)
        middle = time.perf_counter()
        recapture_fragments(db, plan, phi)
        return middle - began, time.perf_counter() - middle

    seen: dict[float, tuple[float, float]] = {}

    def one(i: int) -> Callable[[float], float]:
        return lambda share: seen.setdefault(share, times(share) if share not in seen else seen[share])[i]

    return break_even(one(0), one(1), 0.0, largest, steps)


def break_evens(spark: SparkSession, d: str) -> Iterator[Row]:
    loads = {"having_1": (w.multi_aggregate(1), [BOTH[1]]), "having_3": (w.multi_aggregate(3), [BOTH[1]]), "groups_l_suppkey": (w.grouped("l_suppkey", 56000), [("lineitem", "l_suppkey", 100)]), "groups_l_orderkey": (w.grouped("l_orderkey", 90000), [("lineitem", "l_orderkey", 100)]), "join_part": (w.join_having(46000), BOTH), "join_selective_5": (w.join_having(50000, 5), BOTH)}
    for name, (plan, ranges) in loads.items():
        share = even(spark, d, plan, Partitioning(*(dense(spark, d, *r) for r in ranges)), "lineitem", "l_orderkey")
        yield {"experiment": "break_even", "query": name, "share": share}


EXPERIMENTS: dict[str, Callable[..., Iterator[Row]]] = {"mix": mix, "topk": topk, "eager": eager_cost, "granularity": granularity, "selective": selective, "bloom": bloom, "groups": groups, "joins": joins, "pushdown": pushdown, "tpch": tpch, "memory": memory, "break_even": break_evens}


def main() -> None:
    args = argparse.ArgumentParser()
    args.add_argument("names", nargs="*", choices=[*EXPERIMENTS, []], default=[])
    args.add_argument("--dir", default="/root/testdata/sf0.1")
    args.add_argument("--operations", type=int, default=1000)
    args.add_argument("--cpus", default="*")
    a = args.parse_args()
    spark = SparkSession.builder.master(f"local[{a.cpus}]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in a.names or EXPERIMENTS:
        more = {"mix": {"operations": a.operations}, "topk": {"updates": max(1, a.operations // 2)}, "eager": {"updates": a.operations}}.get(name, {})
        for row in EXPERIMENTS[name](spark, a.dir, **more):
            print(json.dumps(row), flush=True)
    if not a.names or "eager" in a.names:
        for row in eager_cost(spark, a.dir, (50, 200, 1000, 0), min(200, a.operations), join=True):
            print(json.dumps(row), flush=True)


if __name__ == "__main__":
    main()
