"""The registered queries: methods, variants, baselines and workloads on the given tables, with oracle SQL.

The README lists the workloads that are left out or reduced.

Unless its name says otherwise a sketch here was captured at version 0 (rows whose order key is not 0 by 40) and
maintained to version 1 (those inserted, the rows at 1 by 40 deleted); the oracles compute the accurate
sketch, or the answer, from scratch at version 1.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skipsketch import workloads as w
from skipsketch.functions.bloom import BloomIndex
from skipsketch.functions.ranges import GridRanges, Partitioning, RangeSet, annotate, equi_depth_ranges, fragments_in, merge_ranges, ranges_bytes, remap, sketch_bytes, sketch_of, split_range
from skipsketch.operators.maintain import Options, Sketch, answer, capture, maintain, recapture_fragments, with_sketch
from skipsketch.plans.algebra import Aggregate, Filter, Join, Node, Project, Scan, TopK, UnionAll
from skipsketch.plans.safety import is_safe, pushable_predicates
from skipsketch.session import EagerStrategy, FullMaintenance, LazyStrategy, NoSketch, Session
from skipsketch.sources.delta import Database, apply_delta, consolidate, delta_between, signed
from skipsketch.sources.shared import fresh_dir

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    def register(f: Query) -> Query:
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return register


# ---- helpers ---------------------------------------------------------------------------------------------

KEY = {"lineitem": "l_orderkey", "orders": "o_orderkey", "events": "event_id", "part": "p_partkey", "customer": "c_custkey", "supplier": "s_suppkey", "nation": "n_nationkey", "documents": "doc_id"}
#: The dense key of another table that bounds an attribute.
DENSE = {"l_partkey": ("part", "p_partkey"), "p_partkey": ("part", "p_partkey"), "l_orderkey": ("orders", "o_orderkey"), "o_orderkey": ("orders", "o_orderkey"), "o_custkey": ("customer", "c_custkey"), "c_custkey": ("customer", "c_custkey"), "l_suppkey": ("supplier", "s_suppkey"), "s_suppkey": ("supplier", "s_suppkey"), "event_id": ("events", "event_id")}


def dense(spark: SparkSession, d: str, table: str, attr: str, p: int = 100) -> RangeSet:
    return RangeSet(table, attr, w.key_ranges(spark, d, *DENSE[attr], p).cuts)


def frag_sql(attr: str, p: int = 100) -> str:
    """The same ranges in SQL: p equal ranges, the first and last unbounded."""
    t, k = DENSE[attr]
    return f"CAST(least({p} - 1, {attr} // ((SELECT max({k}) + 1 FROM {t}) // {p})) AS INTEGER)"


def rows_of(spark: SparkSession, rows: Iterable[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(list(rows), schema)


def sketch_rows(spark: SparkSession, sketch: Sketch | set[int], phi: Partitioning | None = None) -> DataFrame:
    """tbl, frag; at most a row for each fragment."""
    phi = phi or sketch.phi
    found = sketch if isinstance(sketch, set) else sketch.fragments
    return rows_of(spark, (phi.local(f) for f in sorted(found)), "tbl string, frag int")


def maintained(spark: SparkSession, d: str, plan: Node, ranges: list[tuple[str, str, int]], options: Options | None = None, changed: set[str] | None = None) -> tuple[Database, Sketch, dict[int, int]]:
    db = w.split_database(spark, d, {t: KEY[t] for t in plan.tables()}, changed, commit=False)
    phi = Partitioning(*(dense(spark, d, *r) for r in ranges))
    sketch = capture(db, plan, phi, options=options)
    whole = {t: w.table(spark, d, t) for t in plan.tables()}
    db.update({t: (whole[t].where(f"{KEY[t]} % 40 = 0"), whole[t].where(f"{KEY[t]} % 40 = 1")) for t in sorted(changed or set(plan.tables()))})
    return db, sketch, maintain(db, sketch)


LI1 = "(SELECT * FROM lineitem WHERE l_orderkey % 40 <> 1)"
LI0 = "(SELECT * FROM lineitem WHERE l_orderkey % 40 <> 0)"
OR1 = "(SELECT * FROM orders WHERE o_orderkey % 40 <> 1)"
OR0 = "(SELECT * FROM orders WHERE o_orderkey % 40 <> 0)"


def accurate_sql(table: str, rows: str, key: str, having: str, attr: str, p: int = 100) -> str:
    return f"SELECT DISTINCT '{table}' AS tbl, {frag_sql(attr, p)} AS frag FROM {rows} WHERE {key} IN (SELECT {key} FROM {rows} GROUP BY {key} HAVING {having})"


# ---- ranges and annotation -------------------------------------------------------------------------------


@query(f"SELECT frag, CAST(min(l_partkey) AS BIGINT) AS lo, CAST(max(l_partkey) AS BIGINT) AS hi, count(*) AS n FROM (SELECT l_partkey, {frag_sql('l_partkey')} AS frag FROM lineitem) GROUP BY frag")
def ranges_explicit_partkey(spark: SparkSession, d: str) -> DataFrame:
    rows = annotate(w.table(spark, d, "lineitem").select("l_partkey"), dense(spark, d, "lineitem", "l_partkey"))
    return rows.groupBy(F.col("__frag").alias("frag")).agg(F.min("l_partkey").alias("lo"), F.max("l_partkey").alias("hi"), F.count("*").alias("n"))


@query(f"SELECT frag, count(*) AS n FROM (SELECT {frag_sql('l_orderkey', 500)} AS frag FROM lineitem) GROUP BY frag")
def ranges_many_orderkey(spark: SparkSession, d: str) -> DataFrame:
    """More ranges than one compiled decision tree holds: looked up by binary search in Arrow batches."""
    rows = annotate(w.table(spark, d, "lineitem").select("l_orderkey"), dense(spark, d, "lineitem", "l_orderkey", 500))
    return rows.groupBy(F.col("__frag").alias("frag")).agg(F.count("*").alias("n"))


_cuts = ", ".join(f"percentile_disc({i / 8}) WITHIN GROUP (ORDER BY o_totalprice) AS q{i}" for i in range(1, 8))


@query(f"WITH q AS (SELECT {_cuts} FROM orders) SELECT frag, count(*) AS n FROM (SELECT CAST({' + '.join(f'(o_totalprice >= q{i})::INT' for i in range(1, 8))} AS INTEGER) AS frag FROM orders, q) GROUP BY frag")
def ranges_equidepth_totalprice(spark: SparkSession, d: str) -> DataFrame:
    orders = w.table(spark, d, "orders")
    ranges = equi_depth_ranges(orders, "orders", "o_totalprice", 8, exact=True)
    return annotate(orders, ranges).groupBy(F.col("__frag").alias("frag")).agg(F.count("*").alias("n"))


@query(f"SELECT CAST({frag_sql('l_partkey', 10)} * 5 + CASE WHEN l_quantity < 13 THEN 0 WHEN l_quantity < 25 THEN 1 WHEN l_quantity < 37 THEN 2 ELSE 3 END AS INTEGER) AS cell, count(*) AS n FROM lineitem GROUP BY 1")
def ranges_grid_part_quantity(spark: SparkSession, d: str) -> DataFrame:
    grid = GridRanges("lineitem", (dense(spark, d, "lineitem", "l_partkey", 10), RangeSet("lineitem", "l_quantity", (13.0, 25.0, 37.0))))
    return annotate(w.table(spark, d, "lineitem"), grid).groupBy(F.col("__frag").cast("int").alias("cell")).agg(F.count("*").alias("n"))


@query(f"SELECT sign, {frag_sql('l_partkey')} AS frag, count(*) AS n FROM (SELECT l_partkey, CASE l_orderkey % 40 WHEN 0 THEN 1 ELSE -1 END AS sign FROM lineitem WHERE l_orderkey % 40 < 2) GROUP BY ALL")
def annotate_lineitem_delta(spark: SparkSession, d: str) -> DataFrame:
    db = w.split_database(spark, d, {"lineitem": "l_orderkey"})
    rows = annotate(db["lineitem"].changes(0), dense(spark, d, "lineitem", "l_partkey"))
    return rows.groupBy(F.col("__m").cast("int").alias("sign"), F.col("__frag").alias("frag")).agg(F.count("*").alias("n"))


# ---- deltas ----------------------------------------------------------------------------------------------


@query("SELECT CASE l_orderkey % 40 WHEN 0 THEN 1 ELSE -1 END AS sign, count(*) AS n FROM lineitem WHERE l_orderkey % 40 < 2 GROUP BY 1")
def delta_between_snapshots(spark: SparkSession, d: str) -> DataFrame:
    rows = w.table(spark, d, "lineitem")
    delta = delta_between(rows.where("l_orderkey % 40 <> 0"), rows.where("l_orderkey % 40 <> 1"))
    return delta.groupBy(F.signum("__m").cast("int").alias("sign")).agg(F.sum(F.abs("__m")).alias("n"))


@query(f"SELECT count(*) AS n, CAST(sum(l_partkey) AS BIGINT) AS parts, CAST(sum(l_linenumber) AS BIGINT) AS numbers FROM {LI1}")
def delta_apply(spark: SparkSession, d: str) -> DataFrame:
    rows = w.table(spark, d, "lineitem")
    delta = signed(rows.where("l_orderkey % 40 = 0")).unionByName(signed(rows.where("l_orderkey % 40 = 1"), -1))
    out = apply_delta(rows.where("l_orderkey % 40 <> 0"), delta)
    return out.agg(F.count("*").alias("n"), F.sum("l_partkey").alias("parts"), F.sum("l_linenumber").cast("long").alias("numbers"))


@query("SELECT count(*) AS n FROM lineitem WHERE l_orderkey % 40 = 0")
def delta_consolidated(spark: SparkSession, d: str) -> DataFrame:
    """A row inserted and deleted again within the log cancels."""
    rows = w.table(spark, d, "lineitem")
    db = Database(spark, {"lineitem": rows.where("l_orderkey % 40 <> 0")})
    db.update({"lineitem": (rows.where("l_orderkey % 40 in (0, 1)"), None)})
    db.update({"lineitem": (None, rows.where("l_orderkey % 40 = 1"))})
    return consolidate(db["lineitem"].changes(0)).agg(F.sum("__m").alias("n"))


@query(f"SELECT 0::INTEGER AS version, count(*) AS n FROM {LI0} UNION ALL SELECT 1::INTEGER, count(*) FROM {LI1}")
def time_travel(spark: SparkSession, d: str) -> DataFrame:
    t = w.split_database(spark, d, {"lineitem": "l_orderkey"})["lineitem"]
    return t.as_of(0).agg(F.lit(0).alias("version"), F.count("*").alias("n")).union(t.as_of(1).agg(F.lit(1), F.count("*")))


@query(f"SELECT count(*) AS n FROM {LI1}")
def log_compacted(spark: SparkSession, d: str) -> DataFrame:
    t = w.split_database(spark, d, {"lineitem": "l_orderkey"})["lineitem"]
    t.compact(1)
    return t.as_of().agg(F.count("*").alias("n"))


# ---- capture and use -------------------------------------------------------------------------------------


def captured(spark: SparkSession, d: str, plan: Node, ranges: list[tuple[str, str, int]]) -> tuple[Database, Sketch]:
    db = Database(spark, {t: w.table(spark, d, t) for t in plan.tables()})
    return db, capture(db, plan, Partitioning(*(dense(spark, d, *r) for r in ranges)))


@query(accurate_sql("lineitem", "lineitem", "l_partkey", "sum(l_quantity) > 1100", "l_partkey"))
def capture_sum_having(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, captured(spark, d, w.sum_having(1100), [("lineitem", "l_partkey", 100)])[1])


@query(accurate_sql("lineitem", "lineitem", "l_partkey", "sum(l_quantity) > 1300", "l_orderkey"))
def capture_sum_having_other_attribute(spark: SparkSession, d: str) -> DataFrame:
    """Safe by monotonicity, on an attribute that is no group key."""
    return sketch_rows(spark, captured(spark, d, w.sum_having(1300), [("lineitem", "l_orderkey", 100)])[1])


@query(accurate_sql("orders", "orders", "o_custkey", "avg(o_totalprice) > 345000 AND avg(o_totalprice) < 355000", "o_custkey"))
def capture_avg_interval(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, captured(spark, d, w.avg_interval(345000, 355000), [("orders", "o_custkey", 100)])[1])


@query(accurate_sql("lineitem", "lineitem", "l_partkey", "count(*) > 40", "l_partkey"))
def capture_count_having(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, captured(spark, d, w.count_having(40), [("lineitem", "l_partkey", 100)])[1])


_joined = "(SELECT p_partkey FROM part JOIN {li} ON p_partkey = l_partkey WHERE {where} GROUP BY 1 HAVING avg(l_extendedprice) < {c})"


def join_sql(li: str, where: str, c: float) -> str:
    groups = _joined.format(li=li, where=where, c=c)
    return f"SELECT DISTINCT 'part' AS tbl, {frag_sql('p_partkey')} AS frag FROM part WHERE p_partkey IN {groups} UNION SELECT DISTINCT 'lineitem', {frag_sql('l_partkey')} FROM {li} WHERE l_partkey IN {groups}"


BOTH = [("part", "p_partkey", 100), ("lineitem", "l_partkey", 100)]


@query(join_sql("lineitem", "true", 46000))
def capture_join_having(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, captured(spark, d, w.join_having(46000), BOTH)[1])


@query(f"SELECT DISTINCT 'orders' AS tbl, {frag_sql('o_orderkey')} AS frag FROM orders WHERE o_custkey IN (SELECT DISTINCT o_custkey FROM orders ORDER BY 1 LIMIT 10)")
def capture_topk(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, captured(spark, d, w.top_customers(), [("orders", "o_orderkey", 100)])[1])


@query("SELECT l_partkey, CAST(sum(l_quantity) AS BIGINT) AS qty FROM lineitem GROUP BY 1 HAVING sum(l_quantity) > 1100")
def use_sum_having(spark: SparkSession, d: str) -> DataFrame:
    db, sketch = captured(spark, d, w.sum_having(1100), [("lineitem", "l_partkey", 100)])
    return with_sketch(db, sketch).select("l_partkey", F.col("qty").cast("long").alias("qty"))


@query("SELECT o_custkey FROM orders GROUP BY 1 HAVING avg(o_totalprice) > 345000 AND avg(o_totalprice) < 355000")
def use_avg_interval(spark: SparkSession, d: str) -> DataFrame:
    db, sketch = captured(spark, d, w.avg_interval(345000, 355000), [("orders", "o_custkey", 100)])
    return with_sketch(db, sketch).select("o_custkey")


@query("SELECT o_custkey, CAST(sum(o_totalprice::DECIMAL(20,4)) * 100 AS BIGINT) AS cents FROM orders GROUP BY 1 ORDER BY sum(o_totalprice::DECIMAL(20,4)) DESC, 1 LIMIT 10")
def use_topk(spark: SparkSession, d: str) -> DataFrame:
    db, sketch = captured(spark, d, w.top_spenders(), [("orders", "o_orderkey", 100)])
    return with_sketch(db, sketch).select("o_custkey", (F.col("total") * 100).cast("long").alias("cents"))


@query(f"WITH s AS ({accurate_sql('lineitem', 'lineitem', 'l_partkey', 'sum(l_quantity) > 1100', 'l_partkey')}), g AS (SELECT frag, frag - row_number() OVER (ORDER BY frag) AS island FROM s) SELECT CAST(min(frag) AS INTEGER) AS lo, CAST(max(frag) AS INTEGER) AS hi FROM g GROUP BY island")
def coalesced_runs(spark: SparkSession, d: str) -> DataFrame:
    sketch = captured(spark, d, w.sum_having(1100), [("lineitem", "l_partkey", 100)])[1]
    return rows_of(spark, sketch.phi.ranges["lineitem"].runs(sketch.by_table()["lineitem"]), "lo int, hi int")


# ---- maintenance -----------------------------------------------------------------------------------------


@query(accurate_sql("lineitem", LI1, "l_partkey", "sum(l_quantity) > 1100", "l_partkey"))
def maintain_sum_having(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, maintained(spark, d, w.sum_having(1100), [("lineitem", "l_partkey", 100)])[1])


@query(accurate_sql("lineitem", LI1, "l_partkey", "sum(l_quantity) > 1200", "l_orderkey"))
def maintain_sum_having_other_attribute(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, maintained(spark, d, w.sum_having(1200), [("lineitem", "l_orderkey", 100)])[1])


@query(accurate_sql("lineitem", LI1, "l_partkey", "count(*) > 38", "l_partkey"))
def maintain_count_having(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, maintained(spark, d, w.count_having(38), [("lineitem", "l_partkey", 100)])[1])


@query(accurate_sql("orders", OR1, "o_custkey", "avg(o_totalprice) > 345000 AND avg(o_totalprice) < 355000", "o_custkey"))
def maintain_avg_interval(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, maintained(spark, d, w.avg_interval(345000, 355000), [("orders", "o_custkey", 100)])[1])


for _k in (1, 2, 3, 9):
    QUERIES[f"maintain_multi_agg{_k}"] = lambda spark, d, k=_k: sketch_rows(spark, maintained(spark, d, w.multi_aggregate(k), [("lineitem", "l_partkey", 100)])[1])
    ORACLES[f"maintain_multi_agg{_k}"] = accurate_sql("lineitem", LI1, "l_partkey", "avg(l_extendedprice) > 60000", "l_partkey")

for _key, _c in (("l_quantity", 50000), ("l_suppkey", 53500), ("l_orderkey", 70000)):
    def _by_group(spark: SparkSession, d: str, key: str = _key, c: int = _c) -> DataFrame:
        db = w.split_database(spark, d, {"lineitem": "l_orderkey"}, commit=False)
        ranges = RangeSet("lineitem", key, tuple(float(x) for x in range(2, 51))) if key == "l_quantity" else dense(spark, d, "lineitem", key)
        sketch = capture(db, w.grouped(key, c), Partitioning(ranges))
        rows = w.table(spark, d, "lineitem")
        db.update({"lineitem": (rows.where("l_orderkey % 40 = 0"), rows.where("l_orderkey % 40 = 1"))})
        maintain(db, sketch)
        return sketch_rows(spark, sketch)

    QUERIES[f"maintain_groups_{_key}"] = _by_group
    _f = "CAST(l_quantity - 1 AS INTEGER)" if _key == "l_quantity" else frag_sql(_key)
    ORACLES[f"maintain_groups_{_key}"] = f"SELECT DISTINCT 'lineitem' AS tbl, {_f} AS frag FROM {LI1} WHERE {_key} IN (SELECT {_key} FROM {LI1} GROUP BY 1 HAVING avg(l_extendedprice) > {_c})"


@query(
    f"WITH a AS ({accurate_sql('lineitem', LI0, 'l_partkey', 'sum(l_quantity) > 1100', 'l_partkey')}), b AS ({accurate_sql('lineitem', LI1, 'l_partkey', 'sum(l_quantity) > 1100', 'l_partkey')}) "
    "SELECT *, 1::INTEGER AS sign FROM (SELECT * FROM b EXCEPT SELECT * FROM a) UNION ALL SELECT *, -1::INTEGER FROM (SELECT * FROM a EXCEPT SELECT * FROM b)"
)
def sketch_delta_sum_having(spark: SparkSession, d: str) -> DataFrame:
    _, sketch, changes = maintained(spark, d, w.sum_having(1100), [("lineitem", "l_partkey", 100)])
    return rows_of(spark, ((*sketch.phi.local(f), s) for f, s in changes.items()), "tbl string, frag int, sign int")


@query(f"SELECT DISTINCT 'lineitem' AS tbl, {frag_sql('l_partkey')} AS frag FROM {LI1} WHERE l_quantity * 2 > 98 AND l_extendedprice > 90000")
def maintain_select_project(spark: SparkSession, d: str) -> DataFrame:
    plan = Project(Filter(w.LINEITEM, "l_quantity * 2 > 98 and l_extendedprice > 90000"), (("part", "l_partkey"), ("double_qty", "l_quantity * 2")))
    return sketch_rows(spark, maintained(spark, d, plan, [("lineitem", "l_partkey", 100)])[1])


@query(f"SELECT DISTINCT 'lineitem' AS tbl, {frag_sql('l_partkey')} AS frag FROM {LI1} WHERE l_quantity > 49 AND l_extendedprice > 90000 OR l_quantity < 2 AND l_extendedprice < 10000")
def maintain_union(spark: SparkSession, d: str) -> DataFrame:
    plan = UnionAll(Filter(w.LINEITEM, "l_quantity > 49 and l_extendedprice > 90000"), Filter(w.LINEITEM, "l_quantity < 2 and l_extendedprice < 10000"))
    return sketch_rows(spark, maintained(spark, d, plan, [("lineitem", "l_partkey", 100)])[1])


@query(join_sql(LI1, "true", 46000))
def maintain_join_one_side(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, maintained(spark, d, w.join_having(46000), BOTH, changed={"lineitem"})[1])


_two = f"(SELECT o_custkey FROM {OR1} JOIN {LI1} ON o_orderkey = l_orderkey GROUP BY 1 HAVING sum(l_quantity) > 1500)"
_two_sql = f"SELECT DISTINCT 'orders' AS tbl, {frag_sql('o_custkey')} AS frag FROM {OR1} WHERE o_custkey IN {_two} AND o_orderkey IN (SELECT l_orderkey FROM {LI1}) UNION SELECT DISTINCT 'lineitem', {frag_sql('l_orderkey')} FROM {LI1} JOIN {OR1} ON o_orderkey = l_orderkey WHERE o_custkey IN {_two}"
TWO_SIDES = Filter(Aggregate(Join(w.ORDERS, w.LINEITEM, (("o_orderkey", "l_orderkey"),)), ("o_custkey",), (("qty", "sum", "l_quantity"),)), "qty > 1500")

for _side in ("before", "after", "telescoped"):
    QUERIES[f"maintain_join_two_sides_{_side}"] = lambda spark, d, side=_side: sketch_rows(spark, maintained(spark, d, TWO_SIDES, [("orders", "o_custkey", 100), ("lineitem", "l_orderkey", 100)], Options(side=side))[1])
    ORACLES[f"maintain_join_two_sides_{_side}"] = _two_sql


@query(_two_sql)
def maintain_join_bloom(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, maintained(spark, d, TWO_SIDES, [("orders", "o_custkey", 100), ("lineitem", "l_orderkey", 100)], Options(bloom=True))[1])


for _share in (1, 5, 10):
    _name = "maintain_join_selective" + ("" if _share == 5 else f"_{_share}")
    QUERIES[_name] = lambda spark, d, share=_share: sketch_rows(spark, maintained(spark, d, w.join_having(50000, share), BOTH, changed={"lineitem"})[1])
    ORACLES[_name] = join_sql(LI1, f"p_partkey % 100 < {_share}", 50000)


@query(f"SELECT DISTINCT 'orders' AS tbl, {frag_sql('o_custkey')} AS frag FROM {OR1} a WHERE o_totalprice > 480000 AND EXISTS (SELECT 1 FROM {OR1} b WHERE b.o_custkey = a.o_custkey AND b.o_totalprice < 20000) UNION SELECT DISTINCT 'orders', {frag_sql('o_custkey')} FROM {OR1} b WHERE o_totalprice < 20000 AND EXISTS (SELECT 1 FROM {OR1} a WHERE b.o_custkey = a.o_custkey AND a.o_totalprice > 480000)")
def maintain_join_self(spark: SparkSession, d: str) -> DataFrame:
    other = Scan("orders", ("o_orderkey", "o_custkey", "o_totalprice"), "x_")
    plan = Join(Filter(Scan("orders", ("o_orderkey", "o_custkey", "o_totalprice")), "o_totalprice > 480000"), Filter(other, "x_o_totalprice < 20000"), (("o_custkey", "x_o_custkey"),))
    return sketch_rows(spark, maintained(spark, d, plan, [("orders", "o_custkey", 100)])[1])


@query(
    f"WITH j AS (SELECT o_orderkey, c_custkey, l_partkey FROM customer JOIN {OR1} ON c_custkey = o_custkey JOIN {LI1} ON o_orderkey = l_orderkey WHERE c_acctbal > 9500) "
    f"SELECT DISTINCT 'customer' AS tbl, {frag_sql('c_custkey')} AS frag FROM j UNION SELECT DISTINCT 'orders', {frag_sql('o_orderkey')} FROM j UNION SELECT DISTINCT 'lineitem', {frag_sql('l_partkey')} FROM j"
)
def maintain_join_three_way(spark: SparkSession, d: str) -> DataFrame:
    plan = Join(Join(Filter(w.CUSTOMER, "c_acctbal > 9500"), w.ORDERS, (("c_custkey", "o_custkey"),)), w.LINEITEM, (("o_orderkey", "l_orderkey"),))
    return sketch_rows(spark, maintained(spark, d, plan, [("customer", "c_custkey", 100), ("orders", "o_orderkey", 100), ("lineitem", "l_partkey", 100)], changed={"orders", "lineitem"})[1])


@query(f"SELECT DISTINCT 'orders' AS tbl, {frag_sql('o_custkey')} AS frag FROM {OR1}, nation WHERE o_totalprice > 490000 AND o_custkey < n_nationkey * 10")
def maintain_join_theta(spark: SparkSession, d: str) -> DataFrame:
    plan = Join(Filter(w.ORDERS, "o_totalprice > 490000"), w.NATION, (), "o_custkey < n_nationkey * 10")
    return sketch_rows(spark, maintained(spark, d, plan, [("orders", "o_custkey", 100)], changed={"orders"})[1])


@query(f"SELECT DISTINCT 'orders' AS tbl, {frag_sql('o_custkey')} AS frag FROM {OR1} WHERE o_orderkey IN (SELECT l_orderkey FROM {LI1} GROUP BY 1 HAVING sum(l_quantity) > 250) UNION SELECT DISTINCT 'lineitem', {frag_sql('l_orderkey')} FROM {LI1} WHERE l_orderkey IN (SELECT l_orderkey FROM {LI1} GROUP BY 1 HAVING sum(l_quantity) > 250) AND l_orderkey IN (SELECT o_orderkey FROM {OR1})")
def maintain_large_orders(spark: SparkSession, d: str) -> DataFrame:
    """A join above an aggregation, whose image is its own state."""
    return sketch_rows(spark, maintained(spark, d, w.large_orders(250), [("orders", "o_custkey", 100), ("lineitem", "l_orderkey", 100)], changed={"orders", "lineitem"})[1])


def extremes(spark: SparkSession, d: str, f: str, limit: int | None) -> DataFrame:
    db, sketch, _ = maintained(spark, d, w.extreme(f), [("lineitem", "l_suppkey", 10)], Options(limit=limit))
    op = sketch.ops[sketch.plan]
    return op.image().df.select("l_suppkey", F.round(F.col("price") * 100).cast("long").alias("cents"))


for _f in ("min", "max"):
    for _limit in (None, 1, 20):
        _name = f"maintain_{_f}" + (f"_bounded{_limit}" if _limit else "")
        QUERIES[_name] = lambda spark, d, f=_f, limit=_limit: extremes(spark, d, f, limit)
        ORACLES[_name] = f"SELECT l_suppkey, CAST({_f}(l_extendedprice::DECIMAL(20,4)) * 100 AS BIGINT) AS cents FROM {LI1} GROUP BY 1"


@query(f"SELECT DISTINCT 'lineitem' AS tbl, {frag_sql('l_partkey')} AS frag FROM {LI1} WHERE l_quantity >= 45")
def maintain_distinct(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, maintained(spark, d, w.distinct_pairs(), [("lineitem", "l_partkey", 100)])[1])


_first = f"(SELECT DISTINCT o_custkey FROM {OR1} ORDER BY 1 LIMIT 10)"


for _limit in (None, 20, 50):
    _name = "maintain_topk_key_asc" + (f"_bounded{_limit}" if _limit else "")
    QUERIES[_name] = lambda spark, d, limit=_limit: sketch_rows(spark, maintained(spark, d, w.top_customers(), [("orders", "o_orderkey", 100)], Options(limit=limit))[1])
    ORACLES[_name] = f"SELECT DISTINCT 'orders' AS tbl, {frag_sql('o_orderkey')} AS frag FROM {OR1} WHERE o_custkey IN {_first}"


@query(f"SELECT DISTINCT 'orders' AS tbl, {frag_sql('o_custkey')} AS frag FROM (SELECT o_custkey FROM {OR1} GROUP BY 1 ORDER BY sum(o_totalprice::DECIMAL(20,4)) DESC, 1 LIMIT 10)")
def maintain_topk_value_desc(spark: SparkSession, d: str) -> DataFrame:
    return sketch_rows(spark, maintained(spark, d, w.top_spenders(), [("orders", "o_custkey", 100)])[1])


def q10_sql(lo: str, hi: str, down: bool) -> str:
    best = f"SELECT c_custkey FROM customer JOIN {OR1} ON c_custkey = o_custkey JOIN {LI1} ON o_orderkey = l_orderkey WHERE o_orderdate >= DATE '{lo}' AND o_orderdate < DATE '{hi}' GROUP BY 1 ORDER BY sum(l_extendedprice::DECIMAL(20,4) * (1 - l_discount::DECIMAL(20,4))) {'DESC' if down else 'ASC'}, 1 LIMIT 20"
    return f"SELECT DISTINCT 'customer' AS tbl, {frag_sql('c_custkey')} AS frag FROM ({best})"


for _down in (False, True):
    for _limit in (None, 100):
        _name = f"maintain_q10_{'desc' if _down else 'asc'}" + (f"_bounded{_limit}" if _limit else "")
        QUERIES[_name] = lambda spark, d, down=_down, limit=_limit: sketch_rows(spark, maintained(spark, d, w.returned_revenue("1995-01-01", "1995-04-01", descending=down), [("customer", "c_custkey", 100)], Options(limit=limit), {"orders", "lineitem"})[1])
        ORACLES[_name] = q10_sql("1995-01-01", "1995-04-01", _down)


@query(f"SELECT l_partkey, CAST('lineitem' AS VARCHAR) AS tbl, {frag_sql('l_orderkey', 10)} AS frag, count(*) AS cnt FROM {LI1} GROUP BY ALL")
def state_group_counts(spark: SparkSession, d: str) -> DataFrame:
    _, sketch, _ = maintained(spark, d, w.sum_having(1100), [("lineitem", "l_orderkey", 10)])
    state = next(op for op in sketch.ops.values()).state
    return state.frags.read().where("cnt <> 0").select("l_partkey", F.lit("lineitem").alias("tbl"), "frag", "cnt")


@query(f"SELECT {frag_sql('l_partkey')} AS frag, count(*) AS cnt FROM (SELECT l_partkey FROM {LI1} GROUP BY 1 HAVING sum(l_quantity) > 1000) GROUP BY 1")
def merge_counters(spark: SparkSession, d: str) -> DataFrame:
    _, sketch, _ = maintained(spark, d, w.sum_having(1000), [("lineitem", "l_partkey", 100)])
    return rows_of(spark, sketch.counters.items(), "frag int, cnt long")


# ---- optimizations ---------------------------------------------------------------------------------------


@query("SELECT count(*) AS n FROM lineitem WHERE l_orderkey % 40 < 2 AND l_partkey IN (SELECT p_partkey FROM part WHERE p_partkey % 100 < 5)")
def bloom_filtered_delta(spark: SparkSession, d: str) -> DataFrame:
    """Delta rows that the filter lets pass and that do have a partner: none of those may be missing."""
    db = w.split_database(spark, d, {"lineitem": "l_orderkey"})
    parts = w.table(spark, d, "part").where("p_partkey % 100 < 5").select("p_partkey")
    index = BloomIndex.build(parts, "p_partkey", parts.count())
    kept = index.keep(db["lineitem"].changes(0), "l_partkey")
    return kept.join(parts, kept.l_partkey == parts.p_partkey, "left_semi").agg(F.count("*").alias("n"))


@query("SELECT count(*) AS n FROM lineitem WHERE l_orderkey % 40 < 2 AND l_quantity <= 5")
def pushed_selection_delta(spark: SparkSession, d: str) -> DataFrame:
    db = w.split_database(spark, d, {"lineitem": "l_orderkey"})
    rows = db["lineitem"].changes(0)
    for p in pushable_predicates(w.selective(5, 50000), "lineitem"):
        rows = rows.where(F.expr(p))
    return rows.agg(F.count("*").alias("n"))


# ---- strategies and baselines ----------------------------------------------------------------------------

_end = "(SELECT * FROM orders WHERE o_orderkey % 40 <> 1 AND o_orderkey % 40 <> 2)"
_answer = f"SELECT o_custkey, CAST(sum(o_totalprice::DECIMAL(20,4)) * 100 AS BIGINT) // count(*) AS cents FROM {_end} GROUP BY 1 HAVING avg(o_totalprice) > 329248 AND avg(o_totalprice) < 400000"


def by_strategy(spark: SparkSession, d: str, strategy, plan: Node, warm: Node | None = None) -> Session:  # noqa: ANN001
    orders = w.table(spark, d, "orders")
    s = Session(spark, {"orders": orders.where("o_orderkey % 40 <> 0")}, {"orders": dense(spark, d, "orders", "o_custkey")}, strategy, positive=w.POSITIVE)
    s.query(warm or plan).count()
    s.update({"orders": (orders.where("o_orderkey % 40 = 0"), None)})
    s.update({"orders": (None, orders.where("o_orderkey % 40 = 1"))})
    s.update({"orders": (None, orders.where("o_orderkey % 40 = 2"))})
    return s


for _name, _make in (("lazy_answer", LazyStrategy), ("eager_answer", EagerStrategy), ("eager_answer_batch50", lambda: EagerStrategy(50)), ("full_answer", FullMaintenance), ("none_answer", NoSketch)):
    def _answered(spark: SparkSession, d: str, make=_make) -> DataFrame:  # noqa: ANN001
        plan = Filter(Aggregate(w.ORDERS, ("o_custkey",), (("price", "avg", "o_totalprice"), ("total", "sum", "o_totalprice"), ("n", "count", "*"))), "price > 329248 and price < 400000")
        rows = by_strategy(spark, d, make(), plan).query(plan)
        return rows.select("o_custkey", F.expr("cast(total * 100 as bigint) div n").alias("cents"))

    QUERIES[_name], ORACLES[_name] = _answered, _answer


@query(f"SELECT o_custkey FROM {_end} GROUP BY 1 HAVING avg(o_totalprice) > 345000 AND avg(o_totalprice) < 355000")
def reuse_narrower_interval(spark: SparkSession, d: str) -> DataFrame:
    """The sketch of a wider interval serves a narrower one."""
    s = by_strategy(spark, d, LazyStrategy(), w.avg_interval(329248, 400000))
    out = s.query(w.avg_interval(345000, 355000)).select("o_custkey")
    assert s.counts["captured"] == 1
    return out


def _cut_sql(cuts: Iterable[str]) -> str:
    return " + ".join(f"(l_partkey >= {c})::INT" for c in cuts)


_sevenths = [f"top * {i} // 7" for i in range(1, 7)]
_needed = "(l_partkey >= top * 13 // 28 AND l_partkey < top // 2 OR l_partkey >= top * 11 // 14 AND l_partkey < top * 23 // 28)"


@query(
    f"WITH t AS (SELECT max(p_partkey) + 1 AS top FROM part), l AS (SELECT {_cut_sql(_sevenths)} AS old, {_cut_sql(['top // 14', *_sevenths[1:], 'top // 2'])} AS new, {_needed} AS needed FROM lineitem, t) "
    "SELECT CAST(new AS INTEGER) AS frag, bool_or(old IN (SELECT old FROM l WHERE needed)) AS inside, count(*) AS n, count(*) FILTER (needed) AS needed FROM l GROUP BY new"
)
def split_merge_ranges(spark: SparkSession, d: str) -> DataFrame:
    """A sketch over seven ranges of lineitem's parts: range 3 is split in two, then the first two ranges become one, which is split elsewhere.

    For each of the eight ranges: whether the remapped sketch covers it, its rows, and those that the query needs.
    """
    top = w.table(spark, d, "part").agg(F.max("p_partkey")).first()[0] + 1
    rows, ranges = w.table(spark, d, "lineitem"), dense(spark, d, "lineitem", "l_partkey", 7)
    needed = f"l_partkey >= {top * 13 // 28} and l_partkey < {top // 2} or l_partkey >= {top * 11 // 14} and l_partkey < {top * 23 // 28}"
    sketch = capture(Database(spark, {"lineitem": rows}), Filter(w.LINEITEM, needed), Partitioning(ranges)).fragments
    for change, fragment, *at in ((split_range, 3, top // 2), (merge_ranges, 0), (split_range, 0, top // 14)):
        ranges, moves = change(ranges, fragment, *at)
        sketch = remap(sketch, moves)
    found = annotate(rows.select("l_partkey"), ranges).groupBy(F.col("__frag").alias("frag")).agg(F.count("*").alias("n"), F.count(F.when(F.expr(needed), 1)).alias("needed"))
    return found.select("frag", F.col("frag").isin(sorted(sketch)).alias("inside"), "n", "needed")


# ---- negative controls -----------------------------------------------------------------------------------


@query(f"SELECT l_partkey FROM {LI1} GROUP BY 1 HAVING sum(l_quantity) > 1100 AND {frag_sql('l_partkey').replace('l_partkey //', 'any_value(l_partkey) //')} NOT IN (SELECT frag FROM ({accurate_sql('lineitem', LI0, 'l_partkey', 'sum(l_quantity) > 1100', 'l_partkey')}))")
def stale_negative_control(spark: SparkSession, d: str) -> DataFrame:
    """Groups that a stale sketch loses."""
    db = w.split_database(spark, d, {"lineitem": "l_orderkey"})
    plan, phi = w.sum_having(1100), Partitioning(dense(spark, d, "lineitem", "l_partkey"))
    stale = Sketch(plan, phi, 0, dict.fromkeys(recapture_fragments(db, plan, phi, 0), 1))
    lost = answer(db, plan).select("l_partkey").exceptAll(with_sketch(db, stale).select("l_partkey"))
    return lost


@query(
    f"WITH g AS (SELECT o_custkey FROM orders GROUP BY 1 HAVING avg(o_totalprice) > 345000 AND avg(o_totalprice) < 355000), f AS (SELECT DISTINCT {frag_sql('o_orderkey')} AS frag FROM orders WHERE o_custkey IN (SELECT * FROM g)) "
    f"SELECT o_custkey FROM orders WHERE {frag_sql('o_orderkey')} IN (SELECT frag FROM f) GROUP BY 1 HAVING avg(o_totalprice) > 345000 AND avg(o_totalprice) < 355000 AND o_custkey NOT IN (SELECT * FROM g)"
)
def safety_negative_control(spark: SparkSession, d: str) -> DataFrame:
    """Groups that an attribute lets in which the safety test refuses."""
    plan = w.avg_interval(345000, 355000)
    assert not is_safe(plan, "orders", "o_orderkey", w.POSITIVE) and is_safe(plan, "orders", "o_custkey", w.POSITIVE)
    db, sketch = captured(spark, d, plan, [("orders", "o_orderkey", 100)])
    return with_sketch(db, sketch).select("o_custkey").exceptAll(answer(db, plan).select("o_custkey"))


# ---- measures --------------------------------------------------------------------------------------------


@query(
    "WITH t AS (SELECT max(o_orderkey) + 1 AS top FROM orders), p AS (SELECT p, top, (SELECT count(DISTINCT top * i // p) FROM range(1, 100000) r(i) WHERE i < p AND top * i // p > 0) + 1 AS ranges FROM (VALUES (100), (1000), (10000), (100000)) v(p), t) "
    "SELECT CAST(p AS INTEGER) AS p, any_value(ranges) AS ranges, count(DISTINCT top * least(p - 1, ((o_orderkey + 1) * p - 1) // top) // p) FILTER (o_totalprice > 450000) AS held, "
    "CAST(8 * ((any_value(ranges) + 63) // 64) + 24 AS BIGINT) AS sketch_size, CAST(44 * any_value(ranges) + 108 AS BIGINT) AS ranges_size FROM orders, p GROUP BY p"
)
def sketch_sizes(spark: SparkSession, d: str) -> DataFrame:
    """For p ranges of the orders' key, fewer where there are fewer keys: those that hold an expensive order, and the sizes of that sketch and of the ranges."""
    rows, out = w.table(spark, d, "orders").where("o_totalprice > 450000").select("o_orderkey"), []
    for p in (100, 1000, 10_000, 100_000):
        ranges = dense(spark, d, "orders", "o_orderkey", p)
        held = fragments_in(sketch_of(rows, ranges).collect())  # a row for each 32,768 ranges
        out.append((p, ranges.count, len(held), sketch_bytes(ranges.count), ranges_bytes(ranges.count)))
    return rows_of(spark, out, "p int, ranges long, held long, sketch_size long, ranges_size long")


@query(" UNION ALL ".join(f"SELECT {c}::INTEGER AS threshold, count(DISTINCT frag) AS ranges, (SELECT count(*) FROM lineitem WHERE {frag_sql('l_partkey')} IN (SELECT frag FROM ({accurate_sql('lineitem', 'lineitem', 'l_partkey', f'sum(l_quantity) > {c}', 'l_partkey')}))) AS covered FROM ({accurate_sql('lineitem', 'lineitem', 'l_partkey', f'sum(l_quantity) > {c}', 'l_partkey')})" for c in (1000, 1100, 1150)))
def coverage_by_threshold(spark: SparkSession, d: str) -> DataFrame:
    from skipsketch.metrics import coverage

    rows = []
    for c in (1000, 1100, 1150):
        db, sketch = captured(spark, d, w.sum_having(c), [("lineitem", "l_partkey", 100)])
        rows.append((c, len(sketch.fragments), coverage(w.table(spark, d, "lineitem"), sketch, "lineitem")[0]))
    return rows_of(spark, rows, "threshold int, ranges long, covered long")


@query(" UNION ALL ".join(f"SELECT {p}::INTEGER AS p, count(*) AS ranges FROM ({join_sql(LI1, 'true', 46000).replace('// 100)', f'// {p})').replace('least(100', f'least({p}')}) WHERE tbl = 'lineitem'" for p in (10, 50, 100, 500, 1000)))
def granularity(spark: SparkSession, d: str) -> DataFrame:
    """Ranges in the sketch by the number of ranges; 5000 of them in ``experiments``, as there are fewer parts here."""
    rows = []
    for p in (10, 50, 100, 500, 1000):
        sketch = maintained(spark, d, w.join_having(46000), [("part", "p_partkey", p), ("lineitem", "l_partkey", p)], changed={"lineitem"})[1]
        rows.append((p, len(sketch.by_table()["lineitem"])))
    return rows_of(spark, rows, "p int, ranges long")


# ---- further workloads -----------------------------------------------------------------------------------

EV1 = "(SELECT * FROM events WHERE event_id % 40 <> 1)"


@query(f"SELECT user_id, CAST(day(ts) AS INTEGER) AS day, count(event_id) AS n FROM {EV1} GROUP BY ALL HAVING count(event_id) > 5")
def events_count_by_user_day(spark: SparkSession, d: str) -> DataFrame:
    db, sketch, _ = _events(spark, d, w.events_by_day())
    return with_sketch(db, sketch).select("user_id", F.col("day").cast("int").alias("day"), "n")


@query(f"SELECT event_type, user_id, CAST((day(ts) - 1) // 10 AS INTEGER) AS ten, CAST(hour(ts) // 12 AS INTEGER) AS half, count(event_id) AS n FROM {EV1} GROUP BY ALL HAVING count(event_id) > 5")
def events_four_keys_having(spark: SparkSession, d: str) -> DataFrame:
    db, sketch, _ = _events(spark, d, w.events_four_keys())
    return with_sketch(db, sketch).select("event_type", "user_id", "ten", "half", "n")


def _events(spark: SparkSession, d: str, plan: Node) -> tuple[Database, Sketch, dict[int, int]]:
    db = w.split_database(spark, d, {"events": "event_id"}, commit=False)
    sketch = capture(db, plan, Partitioning(w.key_ranges(spark, d, "events", "user_id", 15)))
    rows = w.table(spark, d, "events")
    db.update({"events": (rows.where("event_id % 40 = 0"), rows.where("event_id % 40 = 1"))})
    return db, sketch, maintain(db, sketch)


@query("SELECT user_id, count(*) AS n FROM (SELECT o_custkey % (SELECT max(user_id) + 1 FROM events) AS u FROM orders WHERE o_orderkey % 40 <> 1) JOIN (SELECT user_id FROM events WHERE event_id % 40 <> 1) ON u = user_id GROUP BY 1 HAVING count(*) > 7000")
def maintain_many_to_many(spark: SparkSession, d: str) -> DataFrame:
    users = w.table(spark, d, "events").agg(F.max("user_id")).first()[0] + 1
    db = w.split_database(spark, d, {"orders": "o_orderkey", "events": "event_id"}, commit=False)
    sketch = capture(db, w.many_to_many(users, 7000), Partitioning(w.key_ranges(spark, d, "events", "user_id", 15)))
    orders, events = w.table(spark, d, "orders"), w.table(spark, d, "events")
    db.update({"orders": (orders.where("o_orderkey % 40 = 0"), orders.where("o_orderkey % 40 = 1")), "events": (events.where("event_id % 40 = 0"), events.where("event_id % 40 = 1"))})
    maintain(db, sketch)
    return with_sketch(db, sketch)


for _kind, _key, _c in (("supplier", "s_suppkey", 50000), ("nation", "s_nationkey", 55000)):
    def _one_to_many(spark: SparkSession, d: str, kind: str = _kind, key: str = _key, c: int = _c) -> DataFrame:
        db = w.split_database(spark, d, {"lineitem": "l_orderkey", "supplier": "s_suppkey"}, {"lineitem"}, commit=False)
        ranges = dense(spark, d, "supplier", "s_suppkey", 10) if kind == "supplier" else RangeSet("supplier", "s_nationkey", (5, 10, 15, 20))
        sketch = capture(db, w.one_to_many(kind, c), Partitioning(ranges))
        rows = w.table(spark, d, "lineitem")
        db.update({"lineitem": (rows.where("l_orderkey % 40 = 0"), rows.where("l_orderkey % 40 = 1"))})
        maintain(db, sketch)
        return with_sketch(db, sketch).select(F.col(key).cast("long").alias("key"))

    QUERIES[f"maintain_one_to_many_{_kind}"] = _one_to_many
    ORACLES[f"maintain_one_to_many_{_kind}"] = f"SELECT CAST({_key} AS BIGINT) AS key FROM supplier JOIN {LI1} ON s_suppkey = l_suppkey WHERE l_quantity >= 10 GROUP BY 1 HAVING avg(l_extendedprice) < {_c}"


@query("SELECT lang, source, count(*) AS n FROM documents WHERE doc_id % 40 <> 1 GROUP BY ALL HAVING count(*) > 8")
def docs_lang_source_having(spark: SparkSession, d: str) -> DataFrame:
    docs = w.table(spark, d, "documents")
    db = Database(spark, {"documents": docs.where("doc_id % 40 <> 0")})
    sketch = capture(db, w.documents_by_source(), Partitioning(RangeSet("documents", "source", ("src1", "src15", "src3", "src6"))))
    db.update({"documents": (docs.where("doc_id % 40 = 0"), docs.where("doc_id % 40 = 1"))})
    maintain(db, sketch)
    return with_sketch(db, sketch)


@query("SELECT user_id, count(*) AS n FROM events GROUP BY 1 HAVING count(*) > 70")
def stream_eager_events(spark: SparkSession, d: str) -> DataFrame:
    """Events arrive through a file stream in ten parts; every trigger maintains the sketch, which then answers."""
    from skipsketch.streaming.feed import feed, signed_stream

    events = w.table(spark, d, "events").drop("props")
    plan = Filter(Aggregate(Scan("events", ("event_id", "user_id")), ("user_id",), (("n", "count", "*"),)), "n > 70")
    s = Session(spark, {"events": events.where("event_id % 10 = 0")}, {"events": w.key_ranges(spark, d, "events", "user_id", 15)}, EagerStrategy())
    s.query(plan).count()
    source = fresh_dir(spark, "feed")
    events.where("event_id % 10 <> 0").repartition(9, F.col("event_id") % 10).write.parquet(source)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 3).parquet(source)
    feed(s, "events", signed_stream(stream), fresh_dir(spark, "feed-checkpoint")).awaitTermination()
    return s.query(plan).select("user_id", "n")


# ---- further measures and variants -----------------------------------------------------------------------


@query("SELECT l_partkey, CAST(sum(l_quantity) AS BIGINT) AS qty FROM lineitem WHERE l_partkey % 2 = 0 GROUP BY 1 HAVING sum(l_quantity) > 700")
def use_many_runs(spark: SparkSession, d: str) -> DataFrame:
    """A sketch of more separate runs than a pushed-down condition names."""
    plan = Filter(Aggregate(Filter(w.LINEITEM, "l_partkey % 2 = 0"), ("l_partkey",), (("qty", "sum", "l_quantity"),)), "qty > 700")
    db = Database(spark, {"lineitem": w.table(spark, d, "lineitem")})
    ranges = RangeSet("lineitem", "l_partkey", tuple(range(1, w.table(spark, d, "part").count())))
    return with_sketch(db, capture(db, plan, Partitioning(ranges))).select("l_partkey", F.col("qty").cast("long").alias("qty"))


@query(accurate_sql("lineitem", LI1, "l_partkey", "sum(l_quantity) > 1100", "l_partkey"))
def maintain_in_memory(spark: SparkSession, d: str) -> DataFrame:
    from skipsketch.operators.memory import MemorySketch

    db = w.split_database(spark, d, {"lineitem": "l_orderkey"}, commit=False)
    phi = Partitioning(dense(spark, d, "lineitem", "l_partkey"))
    sketch = MemorySketch(db, w.sum_having(1100), phi)
    rows = w.table(spark, d, "lineitem")
    db.update({"lineitem": (rows.where("l_orderkey % 40 = 0"), rows.where("l_orderkey % 40 = 1"))})
    sketch.maintain()
    return sketch_rows(spark, sketch.fragments, phi)


@query(f"SELECT DISTINCT 'orders' AS tbl, {frag_sql('o_custkey', 150)} AS frag FROM (SELECT o_custkey FROM {OR1} GROUP BY 1 ORDER BY sum(o_totalprice::DECIMAL(20,4)) DESC, 1 LIMIT 200)")
def maintain_topk_large_k(spark: SparkSession, d: str) -> DataFrame:
    """The first 200 groups by total, kept with their positions; only positions that change are counted."""
    from skipsketch.operators.memory import MemorySketch

    db = w.split_database(spark, d, {"orders": "o_orderkey"}, commit=False)
    phi = Partitioning(dense(spark, d, "orders", "o_custkey", 150))
    sketch = MemorySketch(db, w.top_spenders(200), phi)
    rows = w.table(spark, d, "orders")
    db.update({"orders": (None, rows.where("o_orderkey % 40 = 1"))})
    sketch.maintain()
    db.update({"orders": (rows.where("o_orderkey % 40 = 0"), None)})
    sketch.maintain()
    return sketch_rows(spark, sketch.fragments, phi)


@query(join_sql("(SELECT * FROM lineitem WHERE l_orderkey NOT BETWEEN 101 AND 200)", "p_partkey > 10", 46000))
def maintain_join_held_sides(spark: SparkSession, d: str) -> DataFrame:
    """Small deltas of one side, of the other and of both meet the sides that are held in memory, as far as these are bounded."""
    from skipsketch.operators.memory import MemorySketch

    plan = w.join_having(46000)
    tables = {s.table: w.table(spark, d, s.table).select(*s.columns) for s in plan.scans()}
    items = [tuple(r) for r in tables["lineitem"].where("l_orderkey <= 200").collect()]
    parts = [tuple(r) for r in tables["part"].where("p_partkey <= 20").collect()]
    order, part = tables["lineitem"].columns.index("l_orderkey"), tables["part"].columns.index("p_partkey")
    db, phi = Database(spark, tables), Partitioning(*(dense(spark, d, *r) for r in BOTH))
    sketch = MemorySketch(db, plan, phi)
    back = {"lineitem": ([r for r in items if r[order] <= 100], []), "part": ([r for r in parts if r[part] > 10], [])}
    for changes in ({"lineitem": ([], items)}, {"part": ([], parts)}, back):
        db.version += 1
        for t, (inserts, deletes) in changes.items():
            db[t].commit_rows(db.version, inserts, deletes)
        sketch.maintain()
    return sketch_rows(spark, sketch.fragments, phi)


@query(accurate_sql("lineitem", LI1, "l_partkey", "sum(l_quantity) > 1100", "l_partkey"))
def maintain_restored_sketch(spark: SparkSession, d: str) -> DataFrame:
    """Evicted after its capture, restored from the catalog's files, then maintained."""
    from skipsketch.sources.catalog import SketchStore

    db = w.split_database(spark, d, {"lineitem": "l_orderkey"}, commit=False)
    store = SketchStore(spark)
    store.put("s", capture(db, w.sum_having(1100), Partitioning(dense(spark, d, "lineitem", "l_partkey"))))
    store.evict("s")
    other = SketchStore(spark, store.path)
    other.load()
    rows = w.table(spark, d, "lineitem")
    db.update({"lineitem": (rows.where("l_orderkey % 40 = 0"), rows.where("l_orderkey % 40 = 1"))})
    sketch = other.get("s")
    maintain(db, sketch)
    return sketch_rows(spark, sketch)


@query("SELECT CAST(v AS INTEGER) AS batch, CAST(ceil(20.0 / greatest(1, ceil(v / 10.0))) AS BIGINT) AS maintained FROM (VALUES (1), (10), (20), (50), (100), (200)) t(v)")
def eager_batches(spark: SparkSession, d: str) -> DataFrame:
    """How often twenty updates of ten rows make eager maintenance run, by batch size; rows that wait are counted at the end as one run."""
    orders = w.table(spark, d, "orders").select(*w.ORDERS.columns)
    updates = [[tuple(r) for r in part] for part in _tens(orders.where("o_orderkey < 200").orderBy("o_orderkey").collect())]
    out = []
    for batch in (1, 10, 20, 50, 100, 200):
        s = Session(spark, {"orders": orders}, {"orders": dense(spark, d, "orders", "o_custkey")}, EagerStrategy(batch), positive=w.POSITIVE, backend="memory")
        s.query(w.avg_interval(345000, 355000)).count()
        for rows in updates:
            s.update_rows("orders", deletes=rows)
        if any(s.pending.values()):
            s.query(w.avg_interval(345000, 355000)).count()
        out.append((batch, s.counts["maintained"]))
    return rows_of(spark, out, "batch int, maintained long")


def _tens(rows: list) -> Iterable[list]:
    return (rows[i : i + 10] for i in range(0, len(rows), 10))


@query("SELECT 'groups' AS part, count(DISTINCT l_suppkey) AS n FROM lineitem UNION ALL SELECT 'frags', count(*) FROM (SELECT DISTINCT l_suppkey, l_partkey * 10 // ((SELECT max(p_partkey) + 1 FROM part)) FROM lineitem)")
def state_rows(spark: SparkSession, d: str) -> DataFrame:
    """Rows of an aggregation's state: groups, and groups by fragments where the attribute is no group key."""
    sketch = captured(spark, d, Filter(Aggregate(w.LINEITEM, ("l_suppkey",), (("hi", "max", "l_extendedprice"),)), "hi > 90000"), [("lineitem", "l_partkey", 10)])[1]
    state = next(iter(sketch.ops.values())).state
    return state.groups.read().agg(F.lit("groups").alias("part"), F.count("*").alias("n")).union(state.frags.read().agg(F.lit("frags"), F.count("*")))


@query("SELECT s::INTEGER AS share, count(*) AS fetched FROM lineitem, (VALUES (2), (25), (50), (100)) t(s) WHERE l_orderkey % 40 < 2 AND l_quantity <= s * 0.5 GROUP BY 1")
def pushdown_by_selectivity(spark: SparkSession, d: str) -> DataFrame:
    """Delta rows that are fetched when the selection is pushed down, by how much of the delta it keeps."""
    db = w.split_database(spark, d, {"lineitem": "l_orderkey"})
    out = None
    for share in (2, 25, 50, 100):
        rows = db["lineitem"].changes(0)
        for p in pushable_predicates(w.selective(share * 0.5, 50000), "lineitem"):
            rows = rows.where(F.expr(p))
        one = rows.agg(F.lit(share).alias("share"), F.count("*").alias("fetched"))
        out = one if out is None else out.union(one)
    return out


@query("SELECT o_custkey, CAST(sum(o_totalprice::DECIMAL(20,4)) * 100 AS BIGINT) AS cents FROM orders WHERE o_orderkey % 40 <> 1 GROUP BY 1 ORDER BY sum(o_totalprice::DECIMAL(20,4)) DESC, 1 LIMIT 10")
def sql_frontend_topk(spark: SparkSession, d: str) -> DataFrame:
    """SQL text to a plan, captured, maintained and answered over its sketch."""
    from skipsketch.plans.frontend import from_sql

    w.table(spark, d, "orders").createOrReplaceTempView("skipsketch_orders")
    plan = from_sql(spark, "SELECT o_custkey, sum(o_totalprice) AS total FROM skipsketch_orders GROUP BY o_custkey ORDER BY total DESC LIMIT 10")
    orders = w.table(spark, d, "orders")
    db = Database(spark, {"skipsketch_orders": orders.where("o_orderkey % 40 <> 0")})
    ranges = RangeSet("skipsketch_orders", "o_custkey", dense(spark, d, "orders", "o_custkey").cuts)
    sketch = capture(db, plan, Partitioning(ranges))
    db.update({"skipsketch_orders": (orders.where("o_orderkey % 40 = 0"), orders.where("o_orderkey % 40 = 1"))})
    maintain(db, sketch)
    return with_sketch(db, sketch).select("o_custkey", (F.col("total") * 100).cast("long").alias("cents"))


# ---- what must not go wrong ------------------------------------------------------------------------------


def _changed_session(spark: SparkSession, d: str, name: str, ranges, **more) -> tuple[Session, DataFrame]:  # noqa: ANN001, ANN003
    """A session on a table at version 0, and the whole table; ``_change`` brings it to version 1."""
    rows = w.table(spark, d, name)
    return Session(spark, {name: rows.where(f"{KEY[name]} % 40 <> 0")}, {name: ranges}, positive=w.POSITIVE, **more), rows


def _change(s: Session, name: str, rows: DataFrame) -> None:
    s.update({name: (rows.where(f"{KEY[name]} % 40 = 0"), rows.where(f"{KEY[name]} % 40 = 1"))})


@query(f"SELECT o_orderkey FROM (SELECT o_orderkey, o_custkey FROM {OR1} ORDER BY o_totalprice, o_orderkey LIMIT 60) WHERE o_custkey % 2 = 0")
def safety_topk_below_filter(spark: SparkSession, d: str) -> DataFrame:
    """A condition above a top-k drops some of its rows; a sketch of the others alone would let further rows move up."""
    s, orders = _changed_session(spark, d, "orders", RangeSet("orders", "o_totalprice", tuple(float(x) for x in range(2000, 60000, 1000))))
    plan = Filter(TopK(w.ORDERS, (("o_totalprice", False),), 60), "o_custkey % 2 = 0")
    s.query(plan).count()
    _change(s, "orders", orders)
    return s.query(plan).select("o_orderkey")


@query(f"SELECT l_suppkey AS l_partkey FROM {LI1} GROUP BY 1 HAVING avg(l_quantity::DECIMAL(20,4)) > 26")
def safety_renamed_key(spark: SparkSession, d: str) -> DataFrame:
    """Grouped by another column under the name of the sketched one."""
    s, rows = _changed_session(spark, d, "lineitem", dense(spark, d, "lineitem", "l_partkey"))
    plan = Filter(Aggregate(Project(w.LINEITEM, (("l_partkey", "l_suppkey"), ("l_quantity", "l_quantity"))), ("l_partkey",), (("m", "avg", "l_quantity"),)), "m > 26")
    s.query(plan).count()
    _change(s, "lineitem", rows)
    return s.query(plan).select("l_partkey")


for _backend in ("memory", "tables"):
    def _exact_bound(spark: SparkSession, d: str, backend: str = _backend) -> DataFrame:
        """Sums that meet a decimal bound exactly."""
        s, orders = _changed_session(spark, d, "orders", dense(spark, d, "orders", "o_custkey"), backend=backend)
        total = orders.where("o_orderkey % 40 <> 1").groupBy("o_custkey").agg(F.sum(F.col("o_totalprice").cast("decimal(20,4)")).alias("t"))
        bound = total.orderBy("o_custkey").first()["t"]
        plan = Filter(Aggregate(w.ORDERS, ("o_custkey",), (("total", "sum", "o_totalprice"),)), f"total >= {bound} and total <= {bound}")
        s.query(plan).count()
        _change(s, "orders", orders)
        return s.query(plan).select("o_custkey")

    QUERIES[f"{_backend}_exact_bound"] = _exact_bound
    ORACLES[f"{_backend}_exact_bound"] = f"WITH t AS (SELECT o_custkey, sum(o_totalprice::DECIMAL(20,4)) AS t FROM {OR1} GROUP BY 1) SELECT o_custkey FROM t WHERE t = (SELECT t FROM t ORDER BY o_custkey LIMIT 1)"


@query(
    "SELECT step::INTEGER AS step, count(*) AS groups FROM (SELECT 0 AS step, l_partkey FROM lineitem WHERE l_orderkey % 40 <> 0 GROUP BY 2 HAVING sum(l_quantity) > 900 "
    "UNION ALL SELECT 1, l_partkey FROM lineitem GROUP BY 2 HAVING sum(l_quantity) > 900 UNION ALL SELECT 2, l_partkey FROM lineitem GROUP BY 2 HAVING sum(l_quantity) > 900) GROUP BY 1"
)
def uncommitted_then_committed(spark: SparkSession, d: str) -> DataFrame:
    """Groups before a transaction's inserts, with them while they aren't committed, and after; they count once."""
    rows = w.table(spark, d, "lineitem")
    s = Session(spark, {"lineitem": rows.where("l_orderkey % 40 <> 0")}, {"lineitem": dense(spark, d, "lineitem", "l_partkey")}, positive=w.POSITIVE)
    plan, new = w.sum_having(900), rows.where("l_orderkey % 40 = 0")
    found = [s.query(plan).count(), s.query(plan, extra={"lineitem": signed(new)}).count()]
    s.update({"lineitem": (new, None)})
    found.append(s.query(plan).count())
    sketch = s.store.get(next(iter(s.store.entries)))
    assert sketch.fragments == recapture_fragments(s.db, plan, sketch.phi)
    return rows_of(spark, enumerate(found), "step int, groups long")


@query(f"SELECT l_partkey FROM {LI1} GROUP BY 1 HAVING sum(l_quantity) > 1100")
def small_doubles_having(spark: SparkSession, d: str) -> DataFrame:
    """Sums of doubles of seven and more decimal places."""
    s, rows = _changed_session(spark, d, "lineitem", dense(spark, d, "lineitem", "l_partkey"))
    plan = Filter(Aggregate(Project(w.LINEITEM, (("l_partkey", "l_partkey"), ("q", "l_quantity / 1e7"))), ("l_partkey",), (("s", "sum", "q"),)), "s > 0.00011")
    s.query(plan).count()
    _change(s, "lineitem", rows)
    return s.query(plan).select("l_partkey")


# ---- further methods and workloads -----------------------------------------------------------------------


@query(accurate_sql("lineitem", LI1, "l_partkey", "sum(l_quantity) > 1100", "l_partkey"))
def view_maintenance_sum_having(spark: SparkSession, d: str) -> DataFrame:
    """Baseline: the sketch as a relational view under classical view maintenance, without annotations."""
    db = w.split_database(spark, d, {"lineitem": "l_orderkey"}, commit=False)
    view = w.as_view(w.sum_having(1100), dense(spark, d, "lineitem", "l_partkey"))
    kept = capture(db, view, Partitioning())
    rows = w.table(spark, d, "lineitem")
    db.update({"lineitem": (rows.where("l_orderkey % 40 = 0"), rows.where("l_orderkey % 40 = 1"))})
    maintain(db, kept)
    return kept.ops[view].image().df.select(F.lit("lineitem").alias("tbl"), F.col("frag").cast("int").alias("frag"))


@query(f"SELECT o_orderkey FROM {OR1} ORDER BY o_totalprice DESC, o_orderkey LIMIT 500")
def maintain_topk_large(spark: SparkSession, d: str) -> DataFrame:
    """A large k: only positions that change are handed on, and the state isn't read while the head suffices."""
    db, sketch, _ = maintained(spark, d, TopK(w.ORDERS, (("o_totalprice", True),), 500), [("orders", "o_custkey", 100)])
    op = sketch.ops[sketch.plan]
    at = op.state.keys.index("o_orderkey")
    assert op.refilled == 0
    return rows_of(spark, ((row[at],) for row in op._top()), "o_orderkey long")


#: Rows that go by step, as SQL with the step's number: the smallest groups, any rows, and the two mixed.
_small = "o_custkey IN (SELECT o_custkey FROM (SELECT o_custkey, row_number() OVER (ORDER BY o_custkey) AS r FROM (SELECT DISTINCT o_custkey FROM orders)) WHERE r > {lo} AND r <= {hi})"
_any = "o_orderkey * 7919 % 15013 >= {lo} * 10 AND o_orderkey * 7919 % 15013 < {hi} * 10"
DELETES = {"minimal": [_small] * 6, "random": [_any] * 6, "mix2": [_any, _any, _small] * 2, "mix4": [_any] * 4 + [_small, _any]}

for _kind, _steps in DELETES.items():
    for _limit in (20, 50):
        def _deleted(spark: SparkSession, d: str, steps: list[str] = _steps, limit: int = _limit) -> DataFrame:
            """The first ten groups after each of six updates has deleted rows; the state keeps ``limit`` groups."""
            orders = w.table(spark, d, "orders").select(*w.ORDERS.columns)
            orders.createOrReplaceTempView("orders")
            db = Database(spark, {"orders": orders})
            plan = w.top_customers()
            sketch = capture(db, plan, Partitioning(dense(spark, d, "orders", "o_custkey")), options=Options(limit=limit))
            gone = "false"
            for i, step in enumerate(steps):
                now = step.format(lo=2 * i, hi=2 * i + 2)
                db.update({"orders": (None, orders.where(f"({now}) and not ({gone})"))})
                gone = f"{gone} or ({now})"
                maintain(db, sketch)
            return with_sketch(db, sketch).select("o_custkey")

        QUERIES[f"topk_deletes_{_kind}_limit{_limit}"] = _deleted
        _gone = " OR ".join(f"({x.format(lo=2 * i, hi=2 * i + 2)})" for i, x in enumerate(_steps))
        ORACLES[f"topk_deletes_{_kind}_limit{_limit}"] = f"SELECT DISTINCT o_custkey FROM orders WHERE NOT ({_gone}) ORDER BY 1 LIMIT 10"


@query(f"SELECT l_partkey, p_size FROM (SELECT l_partkey FROM {LI1} GROUP BY 1 HAVING sum(l_quantity) > 1100) JOIN part ON l_partkey = p_partkey")
def maintain_part_volume(spark: SparkSession, d: str) -> DataFrame:
    db, sketch, _ = maintained(spark, d, w.part_volume(1100), BOTH, changed={"lineitem"})
    return with_sketch(db, sketch).select("l_partkey", "p_size")


@query(f"SELECT s_suppkey FROM supplier JOIN {LI1} ON s_suppkey = l_suppkey WHERE l_shipdate >= DATE '1995-03-01' AND l_shipdate < DATE '1995-06-01' GROUP BY 1 ORDER BY sum((l_extendedprice * (1 - l_discount))::DECIMAL(28,12)) DESC, 1 LIMIT 10")
def maintain_top_suppliers(spark: SparkSession, d: str) -> DataFrame:
    db, sketch, _ = maintained(spark, d, w.top_suppliers("1995-03-01", "1995-06-01"), [("supplier", "s_suppkey", 10), ("lineitem", "l_suppkey", 10)], changed={"lineitem"})
    return with_sketch(db, sketch).select("s_suppkey")


@query(f"SELECT l_partkey % 5000 AS bucket FROM {LI1} GROUP BY 1 HAVING avg(l_extendedprice) > 60000")
def maintain_groups_bucket(spark: SparkSession, d: str) -> DataFrame:
    """Grouped by a computed column, which the table holds so that it can carry the ranges."""
    rows = w.table(spark, d, "lineitem").withColumn("bucket", F.expr("l_partkey % 5000"))
    db = Database(spark, {"lineitem": rows.where("l_orderkey % 40 <> 0")})
    plan = Filter(Aggregate(Scan("lineitem", ("bucket", "l_extendedprice")), ("bucket",), (("price", "avg", "l_extendedprice"),)), "price > 60000")
    sketch = capture(db, plan, Partitioning(RangeSet("lineitem", "bucket", tuple(range(50, 5000, 50)))))
    db.update({"lineitem": (rows.where("l_orderkey % 40 = 0"), rows.where("l_orderkey % 40 = 1"))})
    maintain(db, sketch)
    return with_sketch(db, sketch).select("bucket")


@query(accurate_sql("lineitem", LI1, "l_partkey", "sum(l_quantity) > 1100", "l_partkey"))
def maintain_in_batches(spark: SparkSession, d: str) -> DataFrame:
    """A delta longer than ``batch_rows`` is taken in parts by a hash of its rows."""
    return sketch_rows(spark, maintained(spark, d, w.sum_having(1100), [("lineitem", "l_partkey", 100)], Options(batch_rows=1000))[1])


@query("SELECT 'o_custkey' AS chosen, count(*) AS groups FROM (SELECT o_custkey FROM orders GROUP BY 1 HAVING avg(o_totalprice) > 345000 AND avg(o_totalprice) < 355000)")
def chosen_attribute(spark: SparkSession, d: str) -> DataFrame:
    """Of several partitions the session takes the one that is safe for the query and is its group key."""
    s = Session(spark, {"orders": w.table(spark, d, "orders")}, {"orders": [dense(spark, d, "orders", "o_orderkey"), dense(spark, d, "orders", "o_custkey")]}, positive=w.POSITIVE)
    plan = w.avg_interval(345000, 355000)
    return rows_of(spark, [(s.partitioning(plan).ranges["orders"].attr, s.query(plan).count())], "chosen string, groups long")


@query("SELECT l_partkey, CAST(sum(l_quantity) AS BIGINT) AS qty FROM lineitem GROUP BY 1 HAVING sum(l_quantity) > 1100")
def answer_after_balancing(spark: SparkSession, d: str) -> DataFrame:
    """Ranges that inserts overfill are split and thin ones merged; the remapped sketch goes on serving."""
    rows = w.table(spark, d, "lineitem")
    cuts = dense(spark, d, "lineitem", "l_partkey", 10).cuts[1:]  # the first range is twice as wide
    few = rows.where(f"l_partkey < {cuts[0]} and l_orderkey % 10 <> 0")
    s = Session(spark, {"lineitem": rows.where(f"l_partkey >= {cuts[0]} or l_orderkey % 10 = 0")}, {"lineitem": RangeSet("lineitem", "l_partkey", cuts)}, positive=w.POSITIVE)
    plan = w.sum_having(1100)
    s.query(plan).count()
    s.update({"lineitem": (few, None)})
    s.query(plan).count()
    done = s.balance("lineitem", factor=1.5, renew=2.0)
    assert done["split"] and s.counts["captured"] == 1
    return s.query(plan).select("l_partkey", F.col("qty").cast("long").alias("qty"))


@query(" UNION ALL ".join(f"SELECT '{'all' if x is None else x}' AS kept, {'count(*)' if x is None else f'least({x}, count(*))'} AS n FROM (SELECT DISTINCT c_custkey FROM customer JOIN {OR1} ON c_custkey = o_custkey JOIN {LI1} ON o_orderkey = l_orderkey WHERE o_orderdate >= DATE '1995-01-01' AND o_orderdate < DATE '1995-04-01')" for x in (50, 100, None)))
def state_rows_by_limit(spark: SparkSession, d: str) -> DataFrame:
    """Rows that a top-k over four tables keeps as its state."""
    out = []
    for limit in (50, 100, None):
        db = w.split_database(spark, d, {"orders": "o_orderkey", "lineitem": "l_orderkey", "customer": "c_custkey", "nation": "n_nationkey"}, {"orders", "lineitem"})
        sketch = capture(db, w.returned_revenue("1995-01-01", "1995-04-01", descending=True), Partitioning(dense(spark, d, "customer", "c_custkey")), options=Options(limit=limit))
        out.append((str(limit or "all"), sketch.ops[sketch.plan].state.read().where("cnt > 0").count()))
    return rows_of(spark, out, "kept string, n long")


@query("SELECT s::INTEGER AS share, true AS none_lost, true AS fewer FROM (VALUES (1), (5), (10)) t(s)")
def bloom_ablation(spark: SparkSession, d: str) -> DataFrame:
    """With the filter fewer delta rows reach the join than without, and the sketch is the same."""
    out = []
    for share in (1, 5, 10):
        with_filter = maintained(spark, d, w.join_having(50000, share), BOTH, Options(bloom=True), {"lineitem"})[1]
        without = maintained(spark, d, w.join_having(50000, share), BOTH, None, {"lineitem"})[1]
        out.append((share, with_filter.fragments == without.fragments, with_filter.measures.joined < with_filter.measures.fetched))
    return rows_of(spark, out, "share int, none_lost boolean, fewer boolean")


@query()
def eager_cost_by_batch(spark: SparkSession, d: str) -> DataFrame:
    """batch, seconds of a hundred updates of ten rows with eager maintenance of that batch size (0: lazy, one query at the end)."""
    from skipsketch import experiments

    return rows_of(spark, ((r["batch"], r["seconds"]) for r in experiments.eager_cost(spark, d, (1, 50, 1000, 0), 100)), "batch int, seconds double")
