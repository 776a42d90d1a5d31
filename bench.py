"""Headline benchmark: one JSON line.  BENCH_SF_DIR and BENCH_CPUS name the tables and the cores.

For each workload: seconds to bring a sketch up to date after a delta of 10, 100 and 1000 rows (in memory, and of 1000
rows on state tables), to capture it again, to run the query without a sketch, and to run it by plain Spark on a plain
table; medians of ``REPEATS``.  BENCH_LOADS limits the workloads, BENCH_PARTS the parts, both by comma-separated names.
"""

from __future__ import annotations

import json
import os
import random
import statistics
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", "8"))
REPEATS, DELTAS = int(os.environ.get("BENCH_REPEATS", "10")), (10, 100, 1000)


def seconds(work, repeats: int = REPEATS) -> list[float]:  # noqa: ANN001
    out = []
    for _ in range(repeats):
        began = time.perf_counter()
        work()
        out.append(time.perf_counter() - began)
    return out


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", str(CPUS)).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    from skipsketch import workloads as w
    from skipsketch.functions.ranges import Partitioning, RangeSet
    from skipsketch import experiments
    from skipsketch.operators.maintain import answer, capture, maintain, recapture_fragments, with_sketch
    from skipsketch.operators.memory import MemorySketch
    from skipsketch.operators.plain import plain
    from skipsketch.queries import dense
    from skipsketch.session import EagerStrategy, FullMaintenance, LazyStrategy, NoSketch
    from skipsketch.sources.delta import Database
    from skipsketch.sources.shared import fresh_dir

    d = SF_DIR

    def r(table: str, attr: str, p: int = 100) -> RangeSet:
        return dense(spark, d, table, attr, p)

    li = lambda p=100: [r("lineitem", "l_partkey", p)]
    both = lambda p=100: [r("part", "p_partkey", p), r("lineitem", "l_partkey", p)]
    quantity = [RangeSet("lineitem", "l_quantity", tuple(float(x) for x in range(2, 51)))]
    loads = {
        "run_sum_having": (w.sum_having(1150), li(), "lineitem"),
        "having_1_avg": (w.multi_aggregate(1), li(), "lineitem"),
        "having_3_avg": (w.multi_aggregate(3), li(), "lineitem"),
        "having_9_avg": (w.multi_aggregate(9), li(), "lineitem"),
        "groups_50": (w.grouped("l_quantity", 50000), quantity, "lineitem"),
        "groups_1k": (w.grouped("l_suppkey", 56000), [r("lineitem", "l_suppkey")], "lineitem"),
        "groups_150k": (w.grouped("l_orderkey", 90000), [r("lineitem", "l_orderkey")], "lineitem"),
        "avg_interval": (w.avg_interval(345000, 355000), [r("orders", "o_custkey")], "orders"),
        "topk_customers": (w.top_customers(), [r("orders", "o_custkey")], "orders"),
        "join_part": (w.join_having(46000), both(), "lineitem"),
        "join_selective_5": (w.join_having(50000, 5), both(), "lineitem"),
    }
    times: dict[str, float] = {}
    spread: dict[str, float] = {}
    ratio: dict[str, float] = {}
    even: dict[str, float] = {}  # share of the table from which full maintenance is faster than state tables, by bisection

    def note(name: str, found: list[float]) -> float:
        times[name] = round(statistics.median(found), 5)
        spread[name] = round((max(found) - min(found)) / max(1e-9, statistics.median(found)), 3)
        return statistics.median(found)

    wanted = set(filter(None, os.environ.get("BENCH_LOADS", "").split(",")))
    parts = set(filter(None, os.environ.get("BENCH_PARTS", "loads,mixed,synthetic,eager,break_even,bloom,llm").split(",")))
    for name, (plan, ranges, changed) in loads.items():
        if "loads" not in parts or wanted and name not in wanted:
            continue
        phi = Partitioning(*ranges)
        # deltas are taken out of the base first, so that each is inserted and deleted in turn
        key = {"lineitem": "l_orderkey", "orders": "o_orderkey"}[changed]
        tables = {t: w.table(spark, d, t) for t in plan.tables()}
        columns = next(s for s in plan.scans() if s.table == changed).columns
        source = tables[changed].select(*columns).where(f"{key} % 7 = 3").limit(max(DELTAS)).collect()
        tables[changed] = tables[changed].select(*columns).where(f"{key} % 7 <> 3")
        db = Database(spark, tables)
        memory = MemorySketch(db, plan, phi)
        sketch = capture(db, plan, phi)
        full = note(f"{name}_full", seconds(lambda: recapture_fragments(db, plan, phi), 5))
        note(f"{name}_none", seconds(lambda: answer(db, plan).write.format("noop").mode("overwrite").save(), 3))
        note(f"{name}_spark", seconds(lambda: plain(tables, plan).write.format("noop").mode("overwrite").save(), 3))
        note(f"{name}_use", seconds(lambda: with_sketch(db, sketch).write.format("noop").mode("overwrite").save(), 3))
        for n in DELTAS:
            rows = [tuple(x) for x in source[:n]]
            found = []
            for i in range(2 * -(-REPEATS // 2)):
                db.version += 1
                db[changed].commit_rows(db.version, [] if i % 2 else rows, rows if i % 2 else [])
                found += seconds(memory.maintain, 1)
            ratio[f"{name}_d{n}"] = round(full / note(f"{name}_memory_d{n}", found), 1)
        maintain(db, sketch)
        found = []
        for i in range(2 * -(-REPEATS // 2)):
            db.version += 1
            db[changed].commit_rows(db.version, [] if i % 2 else rows, rows if i % 2 else [])
            found += seconds(lambda: maintain(db, sketch), 1)
        ratio[f"{name}_tables_d{DELTAS[-1]}"] = round(full / note(f"{name}_tables_d{DELTAS[-1]}", found), 2)
        memory.maintain()
        assert sketch.fragments == memory.fragments == recapture_fragments(db, plan, phi), name

    operations = list(w.mixed(1, 5, 20, 36, 100_000))
    for strategy in (LazyStrategy(), EagerStrategy(50), FullMaintenance(), NoSketch()) if "mixed" in parts else ():
        times[f"mixed_1U5Q_d20_{strategy.name}"] = round(w.run_mixed(spark, d, operations, strategy)[-1]["cum_seconds"], 3)

    rows, groups = int(os.environ.get("BENCH_SYNTHETIC_ROWS", "5000000")), 5000
    path = fresh_dir(spark, "synthetic")
    if "synthetic" in parts:
        w.write_synthetic(spark, path, rows, groups)
    rng = random.Random(3)
    operations = []
    for i in range(24):
        lo = rng.uniform(10, groups - 60)
        operations.append(w.Operation("update", start=(i // 4) * 500, size=200) if i % 4 == 3 else w.Operation("query", lo=round(lo, 1), hi=round(lo + 40, 1)))
    operations[0] = w.Operation("query", lo=2000, hi=2600)
    operations = [o if o.kind == "update" or i == 0 else w.Operation("query", lo=2000 + o.lo % 500, hi=2040 + o.lo % 500) for i, o in enumerate(operations)]
    for strategy in (LazyStrategy(), EagerStrategy(50), FullMaintenance(), NoSketch()) if "synthetic" in parts else ():
        found = w.run_synthetic(spark, path, operations, strategy, groups)
        times[f"synthetic_mixed_{strategy.name}"] = round(found[-1]["cum_seconds"], 3)
        times[f"synthetic_query_{strategy.name}"] = round(statistics.median(x["seconds"] for x in found[1:] if x["kind"] == "query"), 4)

    if "eager" in parts:  # a thousand updates of ten rows; 0 is lazy
        for r in experiments.eager_cost(spark, d):
            times[f"eager_1000_updates_batch_{r['batch']}"] = round(r["seconds"], 3)
    if "break_even" in parts:
        for name in ("run_sum_having", "join_part"):
            plan, ranges, changed = loads[name]
            even[name] = round(experiments.even(spark, d, plan, Partitioning(*ranges), changed, "l_orderkey", 4), 4)
    kept = {}
    if "bloom" in parts:  # with and without the filter, for a delta of 5 % of the table
        for r in experiments.bloom(spark, d):
            if r["share"] == 5:
                times[f"join_selective_5_large_delta_{'bloom' if r['bloom'] else 'no_bloom'}"] = round(r["seconds"], 3)
                kept["bloom_delta_kept" if r["bloom"] else "bloom_delta_in"] = r["joined"]

    try:
        from skipsketch.llm.queries import QUERIES
    except ImportError:
        QUERIES = {}
    for name, q in QUERIES.items() if "llm" in parts else ():
        times[name] = round(seconds(lambda q=q: q(spark, d).write.format("noop").mode("overwrite").save(), 1)[0], 3)
    headline = [v for k, v in times.items() if "_memory_d" in k or k.endswith("_use")]
    print(json.dumps({"metric": "sum of medians: sketch maintenance in memory and answers over sketches", "value": round(sum(headline), 4), "unit": "sec", "queries": times, "spread": spread, "speedup_over_full": ratio, "break_even_share": even, "counts": kept, "sf": Path(d).name}))


if __name__ == "__main__":
    main()
