"""Grouping with sum, count, average, minimum and maximum, in full and by delta.

State, all additive: for each group its rows and, for each aggregate, its non-null arguments and their sum;
for each group and fragment its rows; for minimum and maximum each value's rows.  A delta is folded to its
groups first, so a common group is small before any shuffle; only touched groups are read.  Where the sketched
attribute of every sketched table is a group key, a group lies in one fragment and the second part is left out.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from skipsketch.functions.ranges import Partitioning, RangeSet
from skipsketch.operators.annotated import SK, Annotated
from skipsketch.plans.algebra import Aggregate, M, UnionAll
from skipsketch.plans.safety import carried, paths
from skipsketch.sources.shared import stored
from skipsketch.sources.state import AdditiveState

#: Doubles are added as decimals of so many places, sums are kept with as many.
PLACES = 12
EXACT, TOTAL = f"decimal(28,{PLACES})", f"decimal(37,{PLACES})"
#: A double whose decimal is off by more than this share can't be added.
LOSS = 1e-9


def argument(df: DataFrame, expr: str) -> Column:
    """Exact arithmetic: doubles become decimals, so that what is added can be taken away again.

    A double that the decimal can't hold (too large, too small, NaN) is an error, not a rounded value.
    """
    col = F.expr(expr)
    kind = df.select(col.alias("x")).schema["x"].dataType
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        exact = col.try_cast(EXACT)
        lost = exact.isNull() | (F.abs(exact.cast("double") - col) > F.abs(col) * LOSS)
        error = F.raise_error(F.concat(F.lit(f"not exact as {EXACT}: "), col.cast("string"))).cast(EXACT)
        return F.when(col.isNotNull() & lost, error).otherwise(exact)
    return col.cast("decimal(20,0)") if isinstance(kind, (T.LongType, T.IntegerType, T.ShortType, T.ByteType)) else col


def total(df: DataFrame, expr: str) -> Column:
    """The sum of an expression times its multiplicity, without losing a decimal place.

    Most doubles are numbers of four places or fewer: these are added as whole numbers, in two parts so that none can
    overflow, which is much cheaper than making a decimal of each.  Whether a double is one is seen by dividing back.
    """
    arg = argument(df, expr)
    kind = df.select(F.expr(expr).alias("x"), arg.alias("y")).schema
    double, kind = isinstance(kind["x"].dataType, T.DoubleType), kind["y"].dataType
    if isinstance(kind, T.DecimalType) and kind.precision > 28:  # a product would drop places
        many = F.raise_error(F.lit("a wide decimal with a multiplicity other than 1")).cast(kind)
        each = F.when(F.col(M) == 1, arg).when(F.col(M) == -1, -arg).otherwise(many)
    else:
        each = arg * F.col(M).cast("decimal(9,0)")
    out = f"decimal(37,{max(PLACES, kind.scale)})" if isinstance(kind, T.DecimalType) else TOTAL
    if not double:
        return F.coalesce(F.sum(each), F.lit(0)).cast(out)
    x = F.expr(expr)
    units = F.rint(x * 10_000)
    plain = (F.abs(x) < 1e8) & (F.abs(F.col(M)) == 1) & (units / 10_000 == x)
    whole = F.when(plain, units.cast("long") * F.col(M))
    high, low = F.sum(F.floor(whole / 1_000_000)), F.sum(F.pmod(whole, F.lit(1_000_000)))
    units = F.coalesce(high, F.lit(0)).cast("decimal(20,0)") * F.lit(1_000_000).cast("decimal(7,0)") + F.coalesce(low, F.lit(0)).cast("decimal(20,0)")
    rest = F.coalesce(F.sum(F.when(x.isNotNull() & ~F.coalesce(plain, F.lit(False)), each)), F.lit(0)).cast(out)
    return ((units * F.lit("0.0001").cast("decimal(5,4)")).cast(out) + rest).cast(out)


def key_columns(node: Aggregate, phi: Partitioning) -> list[tuple[str, str]] | None:
    """For each access to a sketched table the group key that holds its sketched attribute; None if some has none."""
    out = []
    for path in paths(node):
        if path[-1].table in phi:
            r = phi.ranges[path[-1].table]
            if not isinstance(r, RangeSet) or any(isinstance(n, UnionAll) for n in path):
                return None
            held = carried(path, r.attr)[0]
            if not held:
                return None
            out.append((path[-1].table, min(held)))
    return out


@dataclass
class AggregateState:
    groups: AdditiveState
    frags: AdditiveState | None
    values: dict[str, AdditiveState]
    horizons: dict[str, AdditiveState]

    def all(self) -> list[AdditiveState]:
        return [self.groups, *([self.frags] if self.frags else []), *self.values.values()]


class AggregateOp:
    """``limit``: best values kept for each group and minimum or maximum; None keeps all."""

    def __init__(self, spark: SparkSession, node: Aggregate, phi: Partitioning, limit: int | None = None):
        self.spark, self.node, self.phi, self.limit = spark, node, phi, limit
        self.keyed = key_columns(node, phi)
        self.linear = [(n, f, e) for n, f, e in node.aggs if f in ("sum", "count", "avg")]
        self.ordered = [(n, f, e) for n, f, e in node.aggs if f in ("min", "max")]
        if len(self.linear) + len(self.ordered) < len(node.aggs):
            raise ValueError("aggregates are sum, count, avg, min and max")
        self.state: AggregateState | None = None
        self.folded: tuple[DataFrame, DataFrame | None, dict[str, DataFrame]] | None = None  # what the next capture starts from

    def fold(self, child: Annotated) -> tuple[DataFrame, DataFrame | None, dict[str, DataFrame]]:
        """What the rows add to each part of the state."""
        k, df = list(self.node.keys), child.df
        adds = [F.sum(M).alias("cnt")]
        for n, f, e in self.linear:
            if e == "*":
                adds.append(F.sum(M).alias(f"nn_{n}"))
                continue
            adds.append(F.sum(F.when(F.expr(e).isNotNull(), F.col(M)).otherwise(F.lit(0))).alias(f"nn_{n}"))
            if f != "count":
                adds.append(total(df, e).alias(f"sum_{n}"))
        groups = df.groupBy(*k).agg(*adds)
        frags = None
        if self.keyed is None:
            exploded = df.select(*k, F.explode(child.sketch()).alias("frag"), M) if child.wide or len(child.thin) != 1 else df.select(*k, F.col(child.thin[0]).alias("frag"), M)
            frags = exploded.groupBy(*k, "frag").agg(F.sum(M).alias("cnt"))
        values = {n: df.select(*k, F.expr(e).alias("v"), M).where("v is not null").groupBy(*k, "v").agg(F.sum(M).alias("cnt")) for n, _, e in self.ordered}
        return groups, frags, values

    def _sums(self) -> list[str]:
        return ["cnt", *(x for n, f, e in self.linear for x in ([f"nn_{n}"] if f == "count" or e == "*" else [f"nn_{n}", f"sum_{n}"]))]

    def _value(self, n: str, f: str, s: str) -> Column:
        """The aggregate from the state's columns with suffix ``s``."""
        if f == "count":
            return F.col(f"nn_{n}{s}")
        some = F.col(f"nn_{n}{s}") > 0
        if f == "sum":
            return F.when(some, F.col(f"sum_{n}{s}"))
        return F.when(some, (F.col(f"sum_{n}{s}") / F.col(f"nn_{n}{s}")).cast(f"decimal(38,{PLACES})"))

    def _key_sketch(self) -> Column:
        parts = [(self.phi.ranges[t].column(c) + F.lit(self.phi.offset[t])).cast("int") for t, c in self.keyed]
        return F.array_sort(F.array_distinct(F.array(*parts))) if parts else F.array().cast("array<int>")

    def _trim(self, name: str, values: DataFrame) -> tuple[DataFrame, DataFrame]:
        """The best ``limit`` values of each group, and the worst one kept where some were left out."""
        k = list(self.node.keys)
        down = dict((n, f) for n, f, _ in self.ordered)[name] == "max"
        w = Window.partitionBy(*k).orderBy(F.desc("v") if down else F.asc("v"))
        ranked = values.where("cnt > 0").withColumn("__r", F.row_number().over(w)).withColumn("__n", F.count("*").over(Window.partitionBy(*k)))
        kept = ranked.where(F.col("__r") <= self.limit)
        bound = kept.where((F.col("__r") == self.limit) & (F.col("__n") > self.limit)).select(*k, F.col("v").alias("horizon"))
        return kept.select(*k, "v", "cnt"), bound

    def result(self, groups: DataFrame, frags: DataFrame | None, values: dict[str, DataFrame]) -> Annotated:
        """The operator's output from (summed) state rows."""
        k = list(self.node.keys)
        out = groups.where("cnt > 0")
        if frags is not None:
            sk = frags.where("cnt > 0").groupBy(*k).agg(F.array_sort(F.collect_list("frag")).alias(SK))
            out = _join(out, sk, k)
        else:
            out = out.withColumn(SK, self._key_sketch())
        for n, f, _ in self.ordered:
            best = values[n].where("cnt > 0").groupBy(*k).agg((F.min if f == "min" else F.max)("v").alias(n))
            out = _join(out, best, k)
        cols = [*k]
        for n, f, _ in self.node.aggs:
            cols.append(F.col(n) if f in ("min", "max") else self._value(n, f, "").alias(n))
        return Annotated(out.select(*cols, SK, F.lit(1).cast("long").alias(M)), (), True)

    def full(self, child: Annotated) -> Annotated:
        return self.result(*self.fold(child))

    def capture(self, child: Annotated, version: int) -> Annotated:
        """The output over a whole table, and the state that maintenance starts from."""
        k = list(self.node.keys)
        groups, frags, values = self.folded or self.fold(child)
        self.folded = None
        state = AggregateState(AdditiveState(self.spark, k, self._sums()), None, {}, {})
        state.groups.add(version, groups)
        if frags is not None:
            state.frags = AdditiveState(self.spark, [*k, "frag"], ["cnt"])
            state.frags.add(version, frags)
        for n, rows in values.items():
            own = AdditiveState(self.spark, [*k, "v"], ["cnt"])
            if self.limit is not None:
                rows, bound = self._trim(n, stored(rows, "values"))
                state.horizons[n] = AdditiveState(self.spark, [*k, "horizon"], ["__one"])
                state.horizons[n].add(version, bound.withColumn("__one", F.lit(1).cast("long")))
            own.add(version, rows)
            state.values[n] = own
        self.state = state
        for part in state.all():
            part.tend(k)
        return self.result(*self.held())

    def image(self) -> Annotated:
        """The output at the state's version, without reading the tables."""
        return self.result(*self.held())

    def held(self) -> tuple[DataFrame, DataFrame | None, dict[str, DataFrame]]:
        s = self.state
        return s.groups.read(), s.frags.read() if s.frags else None, {n: v.read() for n, v in s.values.items()}

    def snapshot(self) -> AggregateState:
        s = self.state
        return AggregateState(s.groups.snapshot(), s.frags.snapshot() if s.frags else None, {n: v.snapshot() for n, v in s.values.items()}, {n: v.snapshot() for n, v in s.horizons.items()})

    def maintain(self, delta: Annotated, version: int, recapture=None) -> Annotated:  # noqa: ANN001
        """The output's delta: of each touched group the old row out and the new row in.

        What the delta adds to the state is written once, and read back as the delta of the groups.
        ``recapture(groups)`` gives the input's rows of some groups at the new version, for groups whose kept
        values ran out.
        """
        k, s, before = list(self.node.keys), self.state, self.snapshot()
        if s.frags is not None or self.ordered:  # folded more than once
            delta = replace(delta, df=stored(delta.df, "delta"))
        d_groups, d_frags, d_values = self.fold(delta)
        for part in s.all():
            part.tend(k)
        d_groups = s.groups.add(version, d_groups)
        touched = d_groups.select(*k)
        old = before.groups.read(touched)
        sums, kinds = self._sums(), {f.name: f.dataType for f in s.groups.schema}
        new = d_groups.select(*k, *(F.col(c).alias(f"{c}_d") for c in sums))
        both = _join(new, old, k)
        cols = [*k]
        for c in sums:
            was = F.coalesce(c, F.lit(0)).cast(kinds[c])
            cols += [was.alias(f"{c}_o"), (was + F.col(f"{c}_d")).cast(kinds[c]).alias(f"{c}_n")]
        both = both.select(*cols)
        checked = F.when(F.col("cnt_n") < 0, F.raise_error(F.lit("a row is deleted more often than it occurs")).cast("long")).otherwise(F.col("cnt_n"))
        both = both.withColumn("cnt_n", checked)
        if s.frags is not None:
            d_frags = s.frags.add(version, d_frags)
            was = before.frags.read(touched).select(*k, "frag", F.col("cnt").alias("o"), F.col("cnt").alias("n"))
            after = d_frags.select(*k, "frag", F.lit(0).cast("long").alias("o"), F.col("cnt").alias("n"))
            each = was.unionByName(after).groupBy(*k, "frag").agg(F.sum("o").alias("o"), F.sum("n").alias("n"))
            sk = each.groupBy(*k).agg(F.array_sort(F.collect_list(F.when(F.col("o") > 0, F.col("frag")))).alias("sk_o"), F.array_sort(F.collect_list(F.when(F.col("n") > 0, F.col("frag")))).alias("sk_n"))
            both = _join(both, sk, k)
        else:
            both = both.withColumn("sk_o", self._key_sketch()).withColumn("sk_n", F.col("sk_o"))
        for n, f, _ in self.ordered:
            rows, spent = self._inside(n, d_values[n], touched)
            rows = s.values[n].add(version, rows)
            was = before.values[n].read(touched).select(*k, "v", F.col("cnt").alias("o"), F.col("cnt").alias("n"))
            after = rows.select(*k, "v", F.lit(0).cast("long").alias("o"), F.col("cnt").alias("n"))
            each = was.unionByName(after).groupBy(*k, "v").agg(F.sum("o").alias("o"), F.sum("n").alias("n"))
            pick = F.min if f == "min" else F.max
            best = each.groupBy(*k).agg(pick(F.when(F.col("o") > 0, F.col("v"))).alias(f"{n}_o"), pick(F.when(F.col("n") > 0, F.col("v"))).alias(f"{n}_n"))
            if spent is not None:
                best = self._refill(n, f, stored(best, "best"), both, spent, version, recapture)
            both = _join(both, best, k)

        def side(x: str, sign: int) -> Column:
            out = [F.col(f"{n}_{x}").alias(n) if f in ("min", "max") else self._value(n, f, f"_{x}").alias(n) for n, f, _ in self.node.aggs]
            return F.struct(F.col(f"cnt_{x}").alias("__cnt"), *out, F.col(f"sk_{x}").alias(SK), F.lit(sign).cast("long").alias(M))

        sides = both.select(*k, F.explode(F.array(side("o", -1), side("n", 1))).alias("__s")).where("__s.__cnt > 0")
        return Annotated(sides.select(*k, *(F.col(f"__s.`{n}`").alias(n) for n, _, _ in self.node.aggs), F.col(f"__s.{SK}").alias(SK), F.col(f"__s.{M}").alias(M)), (), True)

    def restore(self, saved: AggregateState) -> None:
        self.state = saved

    def _inside(self, name: str, rows: DataFrame, touched: DataFrame) -> tuple[DataFrame, DataFrame | None]:
        """The delta's values within the horizons of their groups, and those horizons."""
        if self.limit is None:
            return rows, None
        k = list(self.node.keys)
        down = dict((n, f) for n, f, _ in self.ordered)[name] == "max"
        h = self.state.horizons[name].read(touched).where("__one > 0").select(*k, "horizon")
        met = _join(rows, h, k)
        within = F.col("horizon").isNull() | (F.col("v") >= F.col("horizon") if down else F.col("v") <= F.col("horizon"))
        return stored(met.where(within).select(*k, "v", "cnt"), "inside"), h

    def _refill(self, n: str, f: str, best: DataFrame, both: DataFrame, horizon: DataFrame, version: int, recapture) -> DataFrame:  # noqa: ANN001
        """Read again the groups that still have rows beyond the horizon but no kept value."""
        k = list(self.node.keys)
        alive = both.where("cnt_n > 0").select(*k)
        spent = stored(_join(best.where(F.col(f"{n}_n").isNull()).select(*k), horizon.withColumn("__h", F.lit(1)), k).where("__h = 1").select(*k), "spent")
        spent = spent.join(alive, k, "left_semi")
        self.recaptured = spent.count()
        if not self.recaptured:
            return best
        fresh = self.fold(recapture(spent))[2][n]
        kept, bound = self._trim(n, stored(fresh, "values"))
        kept = stored(kept, "values")
        self.state.values[n].add(version, kept)
        gone = horizon.join(spent, k, "left_semi").withColumn("__one", F.lit(-1).cast("long"))
        self.state.horizons[n].add(version, gone.select(*k, "horizon", "__one").unionByName(bound.withColumn("__one", F.lit(1).cast("long"))))
        pick = F.min if f == "min" else F.max
        again = kept.groupBy(*k).agg(pick("v").alias("__again"))
        return _join(best, again, k).select(*k, f"{n}_o", F.coalesce(f"{n}_n", "__again").alias(f"{n}_n"))

    recaptured = 0


def _join(left: DataFrame, right: DataFrame, keys: list[str]) -> DataFrame:
    """Left join on keys that may be null; without keys there is one row on each side at most."""
    renamed = right
    on = F.lit(True)
    for c in keys:
        renamed = renamed.withColumnRenamed(c, f"__j_{c}")
        on = on & F.col(c).eqNullSafe(F.col(f"__j_{c}"))
    return left.join(renamed, on, "left").drop(*(f"__j_{c}" for c in keys))
