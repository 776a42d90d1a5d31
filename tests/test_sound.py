"""The query manager against plain Spark: random plans, every backend and strategy; and what once went wrong."""

import random

import pytest

from skipsketch.functions.ranges import Partitioning, RangeSet
from skipsketch.operators.maintain import Options, capture, maintain, recapture_fragments
from skipsketch.operators.plain import plain
from skipsketch.plans.algebra import Aggregate, Filter, Join, Project, Scan, TopK
from skipsketch.plans.safety import can_reuse, implies, is_safe
from skipsketch.session import EagerStrategy, FullMaintenance, LazyStrategy, Session
from skipsketch.sources import state
from skipsketch.sources.delta import Database, signed

T = Scan("t", ("v", "g", "k"))
U = Scan("u", ("a", "b"))
SCHEMA = {"t": "v long, g long, k long", "u": "a long, b long"}


def frame(spark, rows, schema):
    return spark.createDataFrame(list(rows), schema).coalesce(1)


def random_plan(rng):
    """Renaming projections, joins, groupings and top-k in any order."""
    node, columns = T, ["v", "g", "k"]
    if rng.random() < 0.5:
        names = rng.sample(["v", "g", "k"], 3)  # a column under another one's name
        node = Project(node, tuple((a, b) for a, b in zip(["v", "g", "k"], names)))
    if rng.random() < 0.3:
        node, columns = Join(node, U, ((rng.choice(columns), "a"),)), ["v", "g", "k", "a", "b"]
    if rng.random() < 0.3:
        node = TopK(node, ((rng.choice(columns), rng.random() < 0.5),), rng.randrange(2, 6))
    if rng.random() < 0.3:
        node = Filter(node, f"{rng.choice(columns)} >= {rng.randrange(4)}")
    if rng.random() < 0.7:
        key = rng.choice(columns)
        f, arg = rng.choice([("sum", "v"), ("count", "*"), ("avg", "v"), ("min", "v"), ("max", "k")])
        node, columns = Aggregate(node, (key,), (("x", f, arg),)), [key, "x"]
        if rng.random() < 0.6:
            node = Filter(node, f"x {rng.choice(['>', '<', '>='])} {rng.randrange(1, 12)}")
    if rng.random() < 0.3:
        node = TopK(node, ((rng.choice(columns), rng.random() < 0.5),), rng.randrange(1, 4))
        if rng.random() < 0.5:
            node = Filter(node, f"{rng.choice(columns)} >= {rng.randrange(1, 5)}")
    return node


def bag(df):
    return sorted(tuple(round(float(x), 6) for x in r) for r in df.collect())


@pytest.mark.parametrize("seed", range(8))
def test_random_plans_against_plain_spark(spark, seed):
    rng = random.Random(seed)
    rows = {"t": [(rng.randrange(7), rng.randrange(6), rng.randrange(6)) for _ in range(18)], "u": [(rng.randrange(6), rng.randrange(4)) for _ in range(5)]}
    ranges = {"t": [RangeSet("t", c, (1, 2, 3, 4, 5)) for c in ("v", "g", "k")]}
    plans = [p for p in (random_plan(rng) for _ in range(40)) if any(is_safe(p, "t", c, {"v"}) for c in "vgk")][:3]
    make, backend = [(LazyStrategy, "tables"), (EagerStrategy, "tables"), (LazyStrategy, "auto"), (FullMaintenance, "tables")][seed % 4]
    s = Session(spark, {t: frame(spark, r, SCHEMA[t]) for t, r in rows.items()}, ranges, make(), positive={"v"}, backend=backend)
    for step in range(2):
        for p in plans:
            want = bag(plain({t: frame(spark, r, SCHEMA[t]) for t, r in rows.items()}, p))
            assert bag(s.query(p)) == want, (seed, step, p)
        gone = rng.sample(rows["t"], 3)
        new = [(rng.randrange(7), rng.randrange(6), rng.randrange(6)) for _ in range(3)]
        for x in gone:
            rows["t"].remove(x)
        rows["t"] += new
        s.update_rows("t", new, gone)


def one_table(spark, rows, schema="v long, g long, k long", cuts=(1, 2, 3, 4, 5), attr="v", **more):
    return Session(spark, {"t": frame(spark, rows, schema)}, {"t": RangeSet("t", attr, cuts)}, **more)


def test_what_drops_rows_of_a_topk(spark):
    rows = [(i, i, i) for i in range(1, 6)]
    top = TopK(T, (("v", False),), 3)
    s = one_table(spark, rows, cuts=(3,))
    assert [r["v"] for r in s.query(Filter(top, "v >= 3")).collect()] == [3]
    assert not is_safe(Join(top, U, (("v", "a"),)), "t", "v") and is_safe(Aggregate(top, ("g",), (("n", "count", "*"),)), "t", "v")
    grouped = TopK(Aggregate(T, ("g",), (("s", "sum", "v"),)), (("s", False),), 3)
    assert is_safe(grouped, "t", "g") and not is_safe(Filter(grouped, "s >= 3"), "t", "g")


def test_renamed_columns(spark):
    plan = Filter(Aggregate(Project(T, (("k", "g"), ("v", "v"))), ("k",), (("m", "avg", "v"),)), "m > 6")
    assert not is_safe(plan, "t", "k") and is_safe(plan, "t", "g")
    renamed = Filter(Aggregate(Project(T, (("g", "g"), ("v", "v - 5"))), ("g",), (("s", "sum", "v"),)), "s > 3")
    assert not is_safe(renamed, "t", "k", {"v"})
    twice = Filter(Aggregate(Join(T, Scan("t", ("v", "g", "k"), "x_"), (("v", "x_v"),)), ("g", "x_g"), (("n", "count", "*"),)), "n > 0")
    db = one_table(spark, [(1, 0, 0), (1, 5, 0)]).db
    assert capture(db, twice, Partitioning(RangeSet("t", "g", (3,)))).fragments == {0, 1}


def test_conditions_are_not_misread():
    assert not implies("not a > 4", "not a > 3") and not implies("a <=> 7", "a <=> 5") and not implies("a > 3 or b > 9", "a > 4 or b > 9")
    assert implies("a > 1e-5", "a >= 0.00001")
    joined = lambda c: Join(T, U, (), f"v < {c}")
    assert can_reuse(joined(5), joined(3)) and not can_reuse(joined(3), joined(5))


def test_exact_bounds_in_memory(spark):
    rows = [(0.1, 1, 0), (0.05, 2, 0), (0.05, 2, 0), (0.3, 3, 0)]
    plan = Filter(Aggregate(T, ("g",), (("s", "sum", "v"), ("m", "avg", "v"))), "s >= 0.1 and s <= 0.1")
    for backend in ("memory", "tables"):
        s = one_table(spark, rows, "v double, g long, k long", attr="g", backend=backend)
        assert sorted(r["g"] for r in s.query(plan).collect()) == [1, 2]
        s.update_rows("t", [(0.2, 1, 0)], [(0.3, 3, 0)])
        s.update_rows("t", [(0.1, 3, 0)], [])
        assert sorted(r["g"] for r in s.query(plan).collect()) == [2, 3]


def test_small_doubles_and_refused_ones(spark):
    plan = Filter(Aggregate(T, ("g",), (("s", "sum", "v"),)), "s > 0.000015")
    s = one_table(spark, [(1e-5, 1, 0), (2e-5, 2, 0)], "v double, g long, k long", attr="g")
    assert [r["g"] for r in s.query(plan).collect()] == [2]
    for bad in (1e-13, 1e17, float("nan")):
        s = one_table(spark, [(bad, 1, 0)], "v double, g long, k long", attr="g")
        with pytest.raises(Exception, match="not exact"):
            s.query(plan).collect()
    hi = Aggregate(T, ("g",), (("lo", "min", "v"), ("hi", "max", "v")))
    s = one_table(spark, [(1e-13, 1, 0), (float("nan"), 1, 0)], "v double, g long, k long", attr="g")
    assert [(r["lo"], r["hi"] != r["hi"]) for r in s.query(hi).collect()] == [(1e-13, True)]


def test_uncommitted_rows_count_once(spark):
    plan = Filter(Aggregate(T, ("g",), (("s", "sum", "v"),)), "s < 10")
    s = one_table(spark, [(4, 1, 0), (20, 4, 0)], attr="g")
    assert [r["g"] for r in s.query(plan).collect()] == [1]
    row = frame(spark, [(5, 4, 0), (5, 2, 0)], SCHEMA["t"])
    assert sorted(r["g"] for r in s.query(plan, extra={"t": signed(row)}).collect()) == [1, 2]
    sketch = s.store.get(next(iter(s.store.entries)))
    assert sketch.fragments == {1}
    s.update({"t": (row, None)})
    assert sorted(r["g"] for r in s.query(plan).collect()) == [1, 2]
    assert sketch.fragments == recapture_fragments(s.db, plan, sketch.phi) and sketch.counters == {1: 1, 2: 1}


def test_refused_delta_changes_nothing(spark):
    plan = Filter(Aggregate(T, ("g",), (("s", "sum", "v"),)), "s > 1")
    s = one_table(spark, [(4, 1, 0), (20, 4, 0)], attr="g")
    s.query(plan).collect()
    sketch = s.store.get(next(iter(s.store.entries)))
    before = dict(sketch.counters), list(sketch.ops[plan.child].state.groups.parts)
    s.db.update({"t": (None, frame(spark, [(4, 3, 0)], SCHEMA["t"]))})
    with pytest.raises(Exception, match="more often"):
        maintain(s.db, sketch)
    assert (sketch.counters, sketch.ops[plan.child].state.groups.parts, sketch.version) == (*before, 0)


def test_memory_spills_to_tables(spark, monkeypatch):
    from skipsketch.operators import memory

    rows = [(i % 7, i % 6, i) for i in range(60)]
    values = Filter(Aggregate(T, ("g",), (("hi", "max", "v"), ("n", "count", "*"))), "hi > 3")
    joined = Filter(Aggregate(Join(T, U, (("g", "a"),)), ("g",), (("n", "count", "*"),)), "n > 3")
    tables = {"t": frame(spark, rows, SCHEMA["t"]), "u": frame(spark, [(i % 6, 0) for i in range(30)], SCHEMA["u"])}
    for plan, state_limit, delta_limit, kind in ((values, 30, 50_000, "Sketch"), (joined, 2_000_000, 12, "Sketch"), (joined, 2_000_000, 50_000, "MemorySketch")):
        monkeypatch.setattr(memory, "MOST_STATE", state_limit)
        monkeypatch.setattr(memory, "MOST_DELTA", delta_limit)
        s = Session(spark, tables, {"t": RangeSet("t", "g", (2, 4))}, backend="auto")
        s.query(plan).collect()
        s.update_rows("t", [(9, 5, 1), (9, 4, 2), (9, 3, 3)], [rows[0]])
        now = frame(spark, rows[1:] + [(9, 5, 1), (9, 4, 2), (9, 3, 3)], SCHEMA["t"])
        assert bag(s.query(plan)) == bag(plain({**tables, "t": now}, plan))
        assert type(s.store.get(next(iter(s.store.entries)))).__name__ == kind


def test_large_state_in_folders(spark, monkeypatch):
    monkeypatch.setattr(state, "LARGE", 1)
    monkeypatch.setattr(state, "MOST_PARTS", 3)
    monkeypatch.setattr(state, "BUCKETS", 4)
    rng, rows = random.Random(2), [(i % 9, i % 6, i % 5) for i in range(40)]
    plan, phi = Filter(Aggregate(T, ("g",), (("s", "sum", "v"), ("lo", "min", "v"))), "s > 20"), Partitioning(RangeSet("t", "k", (1, 2, 3)))
    db = one_table(spark, rows).db
    sketch = capture(db, plan, phi)
    assert "/buckets-" in sketch.ops[plan.child].state.groups.parts[0][1]
    for _ in range(4):
        gone, new = rng.sample(rows, 3), [(rng.randrange(9), rng.randrange(6), rng.randrange(5)) for _ in range(3)]
        for x in gone:
            rows.remove(x)
        rows += new
        db.version += 1
        db["t"].commit_rows(db.version, new, gone)
        maintain(db, sketch)
    assert len(sketch.ops[plan.child].state.groups.parts) <= 3
    assert sketch.fragments == recapture_fragments(db, plan, phi)


def test_topk_reads_its_state_only_when_the_head_is_short(spark, monkeypatch):
    from skipsketch.operators.topk import TopKOp

    monkeypatch.setattr(TopKOp, "room", property(lambda self: self.node.k + 2))
    rng, rows = random.Random(4), [(rng_v, i % 3, i) for i, rng_v in enumerate(random.Random(1).choices(range(12), k=40))]
    plan, phi = TopK(T, (("v", True),), 4), Partitioning(RangeSet("t", "k", tuple(range(2, 60, 2))))
    db = one_table(spark, rows).db
    sketch = capture(db, plan, phi)
    for i in range(6):
        gone = sorted(rows, key=lambda r: (-r[0], r[1], r[2]))[:2] if i % 3 else rng.sample(rows, 1)
        new = [(rng.randrange(12), 7, 100 + i)] * (1 + i % 2)
        for x in gone:
            rows.remove(x)
        rows += new
        db.version += 1
        db["t"].commit_rows(db.version, new, gone)
        maintain(db, sketch)
        assert sketch.fragments == {phi.ranges["t"].fragment_of(r[2]) for r in sorted(rows, key=lambda r: (-r[0], r[1], r[2]))[:4]}
    assert 0 < sketch.ops[plan].refilled < 6


@pytest.mark.parametrize("block", [1, 2, 512])
def test_ranked_items_against_sorted_lists(monkeypatch, block):
    from skipsketch.operators import ranked

    monkeypatch.setattr(ranked, "BLOCK", block)
    for seed in range(40):
        rng = random.Random(seed)
        pool, k = range(rng.choice([6, 30, 200])), rng.choice([1, 3, 10, 50])
        held = set(rng.sample(pool, rng.randrange(len(pool))))
        items = ranked.Ranked(held)
        for _ in range(30):
            gone = rng.sample(sorted(held), rng.randrange(min(len(held), 8) + 1))
            free = [x for x in pool if x not in held or x in gone]
            new = rng.sample(free, rng.randrange(min(len(free), 8) + 1))
            old, held = held, held - set(gone) | set(new)
            leaving, entering = items.replaced(gone, new, k)
            was, now = set(sorted(old)[:k]), set(sorted(held)[:k])
            assert sorted(leaving) == sorted(was - now) and sorted(entering) == sorted(now - was)
            assert [items[i] for i in range(len(items))] == sorted(held)
            assert all(items.position(x) == i for i, x in enumerate(sorted(held)))
    with pytest.raises(ValueError):
        items.remove(-1)


@pytest.mark.parametrize("down", [False, True])
def test_large_topk_in_memory(spark, down):
    """Groups come, go and tie around the bound of a top-k that holds most of them."""
    from skipsketch.operators.memory import MemorySketch

    rng = random.Random(9)
    rows = [(rng.randrange(6), rng.randrange(30), i) for i in range(60)]
    plan, phi = TopK(Aggregate(T, ("g",), (("s", "sum", "v"),)), (("s", down),), 17), Partitioning(RangeSet("t", "g", tuple(range(1, 30))))
    db = one_table(spark, rows).db
    sketch = MemorySketch(db, plan, phi)
    for i in range(25):
        gone = rng.sample(rows, min(len(rows), rng.randrange(9)))
        new = [(rng.randrange(6), rng.randrange(30), 100 + 10 * i + j) for j in range(rng.randrange(9) if i < 15 else 1)]
        rows = [r for r in rows if r not in gone] + new
        db.version += 1
        db["t"].commit_rows(db.version, new, gone)
        sketch.maintain()
        totals = {}
        for v, g, _ in rows:
            totals[g] = totals.get(g, 0) + v
        first = sorted(totals, key=lambda g: (-totals[g] if down else totals[g], g))[:17]
        assert sketch.counters == {phi.ranges["t"].fragment_of(g): 1 for g in first}


def test_oversized_deltas_in_steps(spark):
    plan, rng = Filter(Aggregate(T, ("g",), (("s", "sum", "v"),)), "s > 12"), random.Random(3)
    db = one_table(spark, [(i % 5, i % 6, i) for i in range(30)]).db
    sketch = capture(db, plan, Partitioning(RangeSet("t", "g", (1, 2, 3, 4))), options=Options(batch_rows=4))
    for n in (2, 1, 9):
        db.version += 1
        db["t"].commit_rows(db.version, [(rng.randrange(9), rng.randrange(6), 0) for _ in range(n)], [])
    maintain(db, sketch)
    assert sketch.version == 3 and sketch.fragments == recapture_fragments(db, plan, sketch.phi)


@pytest.mark.parametrize("name", ["group", "attr", "join"])
def test_one_long_version_in_parts_of_one_step(spark, name):
    """A version of hundreds of parts adds to the state once, not once for each part."""
    from skipsketch.sources.delta import dealt

    rows = [(i % 50, i % 6, i) for i in range(300)]
    child = T if name != "join" else Join(T, U, (("g", "a"),))
    plan = Filter(Aggregate(child, ("g",), (("s", "sum", "v"), ("hi", "max", "k"))), "s > 1200")
    ranges = RangeSet("t", "v", tuple(range(5, 50, 5))) if name == "attr" else RangeSet("t", "g", (1, 2, 3, 4))
    db = Database(spark, {"t": frame(spark, rows, SCHEMA["t"]), "u": frame(spark, [(i, 0) for i in range(5)], SCHEMA["u"])})
    sketch = capture(db, plan, Partitioning(ranges), options=Options(batch_rows=1))
    db.update({"t": (frame(spark, [(7 * i % 50, i % 6, 300 + i) for i in range(120)], SCHEMA["t"]), frame(spark, rows[:80], SCHEMA["t"]))})
    maintain(db, sketch)
    assert sketch.version == 1 and sketch.counters == capture(db, plan, sketch.phi).counters
    assert all(len(part.parts) == 2 for op in sketch.ops.values() for part in op.state.all())
    assert dealt(db["t"].changes(0), 200).rdd.getNumPartitions() == 200


def test_session_chooses_and_balances(spark):
    rows = [(i % 50, i % 40, 0) for i in range(200)]
    ranges = {"t": [RangeSet("t", "v", (10, 20, 30, 40)), RangeSet("t", "g", (10, 20, 30))]}
    s = Session(spark, {"t": frame(spark, rows, SCHEMA["t"])}, ranges, positive={"v"})
    plan = Filter(Aggregate(T, ("g",), (("s", "sum", "v"),)), "s > 120")
    assert s.partitioning(plan).ranges["t"].attr == "g"
    s.query(plan).collect()
    new = [(1, 35, 0)] * 60 + [(1, 31 + i % 8, 1) for i in range(40)]
    s.update_rows("t", new)
    done = s.balance("t", factor=1.5, renew=2.0)
    assert done["split"] > 0 and s.ranges["t"][1].count > 4
    want = bag(plain({"t": frame(spark, rows + new, SCHEMA["t"])}, plan))
    assert bag(s.query(plan)) == want and s.counts["captured"] == 1
    s.update_rows("t", [(2, 5, 2)] * 250)
    assert s.balance("t", renew=0.5)["renewed"] >= 1
    assert bag(s.query(plan)) == bag(plain({"t": frame(spark, rows + new + [(2, 5, 2)] * 250, SCHEMA["t"])}, plan))


def test_bloom_of_two_columns(spark):
    rows = [(i, i % 4, i % 3) for i in range(24)]
    plan = Join(T, Project(U, (("a", "a"), ("b", "b"))), (("g", "a"), ("k", "b")))
    s = Session(spark, {"t": frame(spark, rows, SCHEMA["t"]), "u": frame(spark, [(1, 2), (3, 0)], SCHEMA["u"])}, {})
    sketch = capture(s.db, plan, Partitioning(RangeSet("t", "v", (5, 10, 15))), options=Options(bloom=True))
    s.update_rows("t", [(99, 1, 2), (3, 2, 2)], [rows[3]])
    maintain(s.db, sketch)
    assert sketch.measures.joined < sketch.measures.fetched and sketch.fragments == recapture_fragments(s.db, plan, sketch.phi)


@pytest.mark.parametrize("most", [200_000, 8])
def test_sides_of_joins_in_memory(spark, monkeypatch, most):
    """Deltas of either side or of both, nulls, a flush, a side beyond its bound: as by state tables."""
    from skipsketch.functions.ranges import Partitioning
    from skipsketch.operators import memory
    from skipsketch.operators.maintain import capture
    from skipsketch.sources.delta import Database

    monkeypatch.setattr(memory, "MOST_SIDE", most)
    rng = random.Random(most)
    bags = {"t": [(i % 4, i % 7, i % 3) for i in range(12)], "u": [(i % 5, i % 2) for i in range(10)]}
    bags["t"][0] = (None, 1, 1)
    bags["u"][0] = (None, 1)
    db = Database(spark, {t: frame(spark, rows, SCHEMA[t]) for t, rows in bags.items()})
    phi = Partitioning(RangeSet("t", "g", (2, 4)), RangeSet("u", "a", (1, 3)))
    plan = Filter(Aggregate(Join(T, U, (("g", "a"),)), ("g",), (("n", "count", "*"),)), "n > 3")
    held, tables = memory.MemorySketch(db, plan, phi), capture(db, plan, phi)
    for step, changed in enumerate((("t",), ("t",), ("u",), ("t", "u"), ("t",), ("u",))):
        db.version += 1
        for t in changed:
            gone, width = rng.sample(bags[t], 2), len(bags[t][0])
            new = [tuple(rng.randrange(5) for _ in range(width)) for _ in range(3)]
            for x in gone:
                bags[t].remove(x)
            bags[t] += new
            db[t].commit_rows(db.version, new, gone)
        if step == 4:
            db["u"].flush()
        assert held.maintain() == maintain(db, tables), step
        assert held.counters == tables.counters
    assert any(side.index is not None for side in held.sides.values()) == (most > 8)


@pytest.mark.parametrize(("most_delta", "most_state", "kind"), [(5, 2_000_000, "memory"), (5, 70, "grown"), (5, 3, "tables")])
def test_memory_beyond_its_bounds(spark, monkeypatch, most_delta, most_state, kind):
    """Long deltas are folded to their groups, large states move to tables: as by state tables, none refused."""
    from skipsketch.operators import memory

    monkeypatch.setattr(memory, "MOST_DELTA", most_delta)
    monkeypatch.setattr(memory, "MOST_STATE", most_state)
    rng = random.Random(8)
    rows = [(rng.randrange(9), i % 6 if i % 6 < 5 else None, i) for i in range(30)]
    db = Database(spark, {"t": frame(spark, rows, SCHEMA["t"]), "u": frame(spark, [(i % 4, i) for i in range(8)], SCHEMA["u"])})
    by_group, by_row = Partitioning(RangeSet("t", "g", (1, 2, 3, 4))), Partitioning(RangeSet("t", "k", tuple(range(3, 120, 3))))
    total = Aggregate(T, ("g",), (("s", "sum", "v"), ("n", "count", "*")))
    plans = [
        (Filter(total, "s > 20"), by_group),
        (Filter(Aggregate(T, ("g",), (("s", "avg", "v"), ("lo", "min", "k"), ("hi", "max", "v"))), "hi > 5"), by_row),
        (TopK(total, (("s", True),), 3), by_group),
        (Filter(Aggregate(Join(T, U, (("g", "a"),)), ("g",), (("n", "count", "*"),)), "n > 11"), by_group),
    ]
    if kind != "memory":
        plans = plans[1:2] if kind == "grown" else plans[:3:2]
    both = [(memory.MemorySketch(db, plan, phi), capture(db, plan, phi)) for plan, phi in plans]
    for step in range(3):
        gone = rng.sample(rows, 6)
        new = [(rng.randrange(9), rng.choice([0, 1, 2, 3, 7 + step, None]), 100 * step + i) for i in range(18)]
        rows = [r for r in rows if r not in gone] + new
        db.update({"t": (frame(spark, new, SCHEMA["t"]), frame(spark, gone, SCHEMA["t"]))})
        for held, tables in both:
            assert held.maintain() == maintain(db, tables), (step, held.plan)
            assert held.counters == tables.counters
    for held, _ in both:
        assert (held.tables is None) == (kind == "memory")
        assert held.tables is not None or held.entries == sum(g.entries() for g in held.groups.values())
    if kind == "tables":
        with pytest.raises(memory.TooLarge):
            memory.MemorySketch(db, *plans[0], strict=True)


def test_state_of_a_join_without_fragments_that_its_keys_tell(spark, monkeypatch):
    """Both sides are sketched by the group key: the state in memory is its groups, and sides are held as before."""
    from skipsketch.operators import memory

    monkeypatch.setattr(memory, "MOST_STATE", 12)
    rows, others = [(i % 4, i % 10, i) for i in range(40)], [(i, i) for i in range(12)]
    db = Database(spark, {"t": frame(spark, rows, SCHEMA["t"]), "u": frame(spark, others, SCHEMA["u"])})
    phi = Partitioning(RangeSet("t", "g", (2, 4, 6)), RangeSet("u", "a", (3, 5)))
    plan = Filter(Aggregate(Join(T, U, (("g", "a"),)), ("a",), (("s", "sum", "v"),)), "s > 5")
    held, tables = memory.MemorySketch(db, plan, phi, strict=True), capture(db, plan, phi)
    for changes in ({"t": ([(9, 11, 1), (3, 0, 2)], rows[:3])}, {"u": ([(10, 0)], others[2:4])}, {"t": ([], rows[4:6]), "u": (others[2:3], [])}):
        db.version += 1
        for t, (new, gone) in changes.items():
            db[t].commit_rows(db.version, new, gone)
        assert held.maintain() == maintain(db, tables)
        assert held.counters == tables.counters and held.entries == len(held.groups)


@pytest.mark.parametrize("down", [False, True])
def test_long_delta_under_a_large_topk_in_memory(spark, monkeypatch, down):
    """Groups replaced a few at a time end up as the first k that they are together."""
    from skipsketch.operators import memory

    monkeypatch.setattr(memory, "MOST_DELTA", 4)
    rng = random.Random(5)
    rows = [(rng.randrange(6), rng.randrange(40), i) for i in range(80)]
    plan, phi = TopK(Aggregate(T, ("g",), (("s", "sum", "v"),)), (("s", down),), 21), Partitioning(RangeSet("t", "g", tuple(range(1, 40))))
    db = Database(spark, {"t": frame(spark, rows, SCHEMA["t"])})
    sketch = memory.MemorySketch(db, plan, phi)
    for step in range(3):
        gone = rng.sample(rows, 30)
        new = [(rng.randrange(6), rng.randrange(40), 100 * step + 100 + j) for j in range(25)]
        rows = [r for r in rows if r not in gone] + new
        db.update({"t": (frame(spark, new, SCHEMA["t"]), frame(spark, gone, SCHEMA["t"]))})
        sketch.maintain()
        totals = {}
        for v, g, _ in rows:
            totals[g] = totals.get(g, 0) + v
        first = sorted(totals, key=lambda g: (-totals[g] if down else totals[g], g))[:21]
        assert sketch.tables is None and sketch.counters == {phi.ranges["t"].fragment_of(g): 1 for g in first}


@pytest.mark.parametrize("kind", ["sums", "join", "topk"])
def test_largest_state_in_memory_fits_a_driver(spark, kind):
    """What groups take in Python, times the bound: 400 MB at most, beside Spark's heap."""
    import gc
    import tracemalloc

    from skipsketch.operators import memory

    db = Database(spark, {"t": frame(spark, [(i % 97, i, i) for i in range(4000)], SCHEMA["t"]), "u": frame(spark, [(i, i) for i in range(4000)], SCHEMA["u"])})
    phi = Partitioning(RangeSet("t", "g", tuple(range(40, 4000, 40))), *([RangeSet("u", "a", tuple(range(40, 4000, 40)))] if kind == "join" else []))
    total = Aggregate(Join(T, U, (("g", "a"),)) if kind == "join" else T, ("g",), (("s", "sum", "v"),))
    plan = TopK(total, (("s", True),), 200) if kind == "topk" else Filter(total, "s > 20")
    memory.MemorySketch(db, plan, phi)  # what is made once is left out
    gc.collect()
    tracemalloc.start()
    try:
        sketch = memory.MemorySketch(db, plan, phi)
        gc.collect()
        held = tracemalloc.get_traced_memory()[0]
    finally:
        tracemalloc.stop()
    assert sketch.tables is None and sketch.entries == 4000
    assert held / sketch.entries * memory.MOST_STATE < 400e6


def test_large_state_of_a_join_is_folded_once(spark, monkeypatch):
    """A state that turns out too large for memory becomes tables without its rows being joined again."""
    from skipsketch.operators import memory
    from skipsketch.operators.aggregate import AggregateOp

    rows, others = [(i % 4, i % 10, i) for i in range(40)], [(i, i) for i in range(12)]
    db = Database(spark, {"t": frame(spark, rows, SCHEMA["t"]), "u": frame(spark, others, SCHEMA["u"])})
    phi = Partitioning(RangeSet("t", "g", (2, 4, 6)), RangeSet("u", "b", (3, 5)))
    joined = Aggregate(Join(T, U, (("g", "a"),)), ("a",), (("s", "sum", "v"), ("hi", "max", "v"), ("n", "count", "*")))
    plan = Filter(joined, "s > 5")
    tables, calls, fold = capture(db, plan, phi), [], AggregateOp.fold
    monkeypatch.setattr(memory, "MOST_STATE", 3)
    monkeypatch.setattr(AggregateOp, "fold", lambda self, child: calls.append(1) or fold(self, child))
    held = memory.MemorySketch(db, plan, phi)
    assert held.tables is not None and len(calls) == 1 and held.counters == tables.counters
    for changes in ({"t": ([(9, 11, 1), (3, 0, 2)], rows[:3])}, {"u": ([(10, 0)], others[2:4])}, {"t": ([], rows[4:6]), "u": (others[2:3], [])}):
        db.version += 1
        for t, (new, gone) in changes.items():
            db[t].commit_rows(db.version, new, gone)
        assert held.maintain() == maintain(db, tables)
        assert held.counters == tables.counters


def test_sizes_are_those_of_a_given_table(spark, tmp_path):
    from skipsketch.queries import QUERIES

    rows = [(i, 1, 460000.0 if i in (4, 5, 149) else 100.0, None) for i in range(150)]
    frame(spark, rows, "o_orderkey long, o_custkey long, o_totalprice double, o_orderdate timestamp").write.parquet(f"{tmp_path}/orders.parquet")
    found = [tuple(r) for r in QUERIES["sketch_sizes"](spark, str(tmp_path)).collect()]
    assert found == [(100, 100, 2, 40, 4508), *((p, 150, 3, 48, 6708) for p in (1000, 10_000, 100_000))]


def test_split_and_merged_ranges_of_a_given_table(spark, tmp_path):
    from pyspark.sql import functions as F

    from skipsketch.queries import QUERIES
    from skipsketch.workloads import LINEITEM

    frame(spark, [(i, 1) for i in range(28)], "p_partkey long, p_size int").write.parquet(f"{tmp_path}/part.parquet")
    rows = frame(spark, [(i,) for i in range(28) for _ in range(1 + i % 2)], "l_partkey long")
    others = [F.lit(1.0).alias(c) for c in LINEITEM.columns if c != "l_partkey"]
    rows.where("l_partkey <> 22").select("l_partkey", *others).write.parquet(f"{tmp_path}/lineitem.parquet")
    found = sorted(tuple(r) for r in QUERIES["split_merge_ranges"](spark, str(tmp_path)).collect())
    # bounds 2, 8, 12, 14, 16, 20, 24; part 13 is needed of range 3, and 22, which has no rows, of range 5
    assert found == [(0, False, 3, 0), (1, False, 9, 0), (2, False, 6, 0), (3, True, 3, 2), (4, True, 3, 0), (5, False, 6, 0), (6, False, 5, 0), (7, False, 6, 0)]
