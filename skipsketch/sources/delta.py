"""Bags, deltas and versioned tables.

A delta is a table's rows with a signed multiplicity ``__m``.  A versioned table is a base snapshot and a log
of deltas partitioned by version; reading a version is the union of both, and consolidating (one shuffle) is
left to those who need plain rows.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from skipsketch.plans.algebra import M
from skipsketch.sources.shared import fresh_dir

VERSION = "__version"


def signed(df: DataFrame, sign: int = 1) -> DataFrame:
    return df.withColumn(M, F.lit(sign).cast("long"))


def consolidate(delta: DataFrame) -> DataFrame:
    """One row for each tuple with its net multiplicity; what cancels goes."""
    cols = [c for c in delta.columns if c != M]
    return delta.groupBy(*cols).agg(F.sum(M).alias(M)).where(F.col(M) != 0)


def delta_between(old: DataFrame, new: DataFrame) -> DataFrame:
    """The symmetric difference of two bags."""
    return consolidate(signed(old, -1).unionByName(signed(new)))


def expand(bag: DataFrame) -> DataFrame:
    """Rows repeated by their multiplicity; a negative one is an error."""
    cols = [c for c in bag.columns if c != M]
    n = F.when(F.col(M) < 0, F.raise_error(F.lit("a row is deleted more often than it occurs")).cast("int")).otherwise(F.col(M).cast("int"))
    return bag.where(F.col(M) != 0).withColumn("__i", F.explode(F.sequence(F.lit(1), n))).select(*cols)


def apply_delta(df: DataFrame, delta: DataFrame) -> DataFrame:
    """The bag after deletes and inserts."""
    return expand(consolidate(signed(df).unionByName(delta.select(*df.columns, M))))


def batches(delta: DataFrame, n: int) -> list[DataFrame]:
    """The delta in n parts by a hash of its rows; their order doesn't matter once it is consolidated."""
    cols = [c for c in delta.columns if c != M]
    return [delta.where(F.pmod(F.xxhash64(*cols), F.lit(n)) == i) for i in range(n)]


def dealt(delta: DataFrame, n: int) -> DataFrame:
    """The delta with its rows dealt out to n tasks by a hash; a row's inserts and deletes meet in one task."""
    return delta.repartition(n, *(c for c in delta.columns if c != M))


@dataclass
class VersionedTable:
    """``base`` is version ``first``; ``log`` has the number of delta rows of each later version."""

    spark: SparkSession
    name: str
    base: DataFrame
    first: int = 0
    path: str = ""
    log: dict[int, int] = field(default_factory=dict)
    recent: dict[int, list[tuple]] = field(default_factory=dict)  # small deltas that still are on the driver

    def __post_init__(self) -> None:
        self.path = self.path or fresh_dir(self.spark, f"log-{self.name}")

    @property
    def columns(self) -> list[str]:
        return self.base.columns

    @cached_property
    def delta_schema(self) -> T.StructType:
        return T.StructType([*self.base.schema.fields, T.StructField(M, T.LongType())])

    @property
    def version(self) -> int:
        return max(self.log, default=self.first)

    def commit(self, version: int, inserts: DataFrame | None = None, deletes: DataFrame | None = None) -> int:
        """Append a delta; returns its number of rows."""
        if version <= self.version:
            raise ValueError("versions only grow")
        parts = [signed(d.select(*self.columns), s) for d, s in ((inserts, 1), (deletes, -1)) if d is not None]
        if not parts:
            return 0
        delta = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
        return self.commit_delta(version, delta)

    def commit_delta(self, version: int, delta: DataFrame) -> int:
        where = f"{self.path}/{VERSION}={version}"
        delta.select(*self.columns, M).write.parquet(where)
        self.log[version] = self.spark.read.parquet(where).count()  # answered from the files' footers
        return self.log[version]

    def commit_rows(self, version: int, inserts: list[tuple] = (), deletes: list[tuple] = ()) -> int:
        """Append a small delta given as rows; it stays on the driver until ``flush``."""
        if version <= self.version:
            raise ValueError("versions only grow")
        self.recent[version] = [(*r, 1) for r in inserts] + [(*r, -1) for r in deletes]
        self.log[version] = len(self.recent[version])
        return self.log[version]

    def flush(self) -> None:
        """Write the deltas that are on the driver into the log."""
        for v in list(self.recent):
            self.spark.createDataFrame(self.recent[v], self.delta_schema).write.parquet(f"{self.path}/{VERSION}={v}")
            del self.recent[v]

    def rows_between(self, since: int, until: int | None = None) -> int:
        """Delta rows in the log after ``since``, from what was noted at their commit; no job runs."""
        until = self.version if until is None else until
        return sum(n for v, n in self.log.items() if since < v <= until)

    def changes(self, since: int, until: int | None = None) -> DataFrame:
        """Signed rows of the versions after ``since``; other versions' folders aren't read."""
        until = self.version if until is None else until
        paths = [f"{self.path}/{VERSION}={v}" for v in sorted(self.log) if since < v <= until and v not in self.recent]
        schema = self.delta_schema
        rows = [r for v in sorted(self.recent) if since < v <= until for r in self.recent[v]]
        written = self.spark.read.schema(schema).parquet(*paths) if paths else None
        if written is None or rows:
            held = self.spark.createDataFrame(rows, schema)
            return held if written is None else written.unionByName(held)
        return written

    def image(self, version: int | None = None) -> DataFrame:
        """The table at a version as signed rows, not consolidated."""
        version = self.version if version is None else version
        if version < self.first:
            raise ValueError("that version is no longer kept")
        base = signed(self.base)
        return base.unionByName(self.changes(self.first, version)) if any(v <= version for v in self.log) else base

    def as_of(self, version: int | None = None) -> DataFrame:
        """The table's rows at a version."""
        version = self.version if version is None else version
        return expand(consolidate(self.image(version))) if any(v <= version for v in self.log) else self.base

    def compact(self, version: int) -> None:
        """Make ``version`` the new base and forget older versions."""
        from skipsketch.sources.shared import stored

        self.base = stored(self.as_of(version), f"base-{self.name}")
        self.first = version
        self.log = {v: n for v, n in self.log.items() if v > version}


class Database:
    """Versioned tables under one version counter."""

    def __init__(self, spark: SparkSession, tables: dict[str, DataFrame]):
        self.spark = spark
        self.tables = {n: VersionedTable(spark, n, df) for n, df in tables.items()}
        self.version = 0

    def __getitem__(self, name: str) -> VersionedTable:
        return self.tables[name]

    def update(self, changes: dict[str, tuple[DataFrame | None, DataFrame | None]]) -> int:
        """Commit inserts and deletes of any tables as one version."""
        self.version += 1
        for name, (inserts, deletes) in changes.items():
            self[name].commit(self.version, inserts, deletes)
        return self.version
