"""Operator state as additive tables.

The state of every stateful operator is a multiset: rows with counts and sums that deltas add to.  So a state
is a log too: each maintenance appends its own additive rows and rewrites nothing, a read sums the parts of
the keys that it asks for, and compaction folds the parts.  Parts are named by version, so older versions of
a sketch keep reading theirs.  A large state is compacted into folders by a hash of its keys, of which a
maintenance reads those that its delta touches.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from skipsketch.sources.shared import fresh_dir

BUCKET = "__b"
#: Folders of a large state, bytes from which a state is large, and parts after which they are folded.
BUCKETS, LARGE, MOST_PARTS = 1024, 256 << 20, 16


@dataclass
class AdditiveState:
    """Rows of ``keys`` with ``sums``, which add up over the parts."""

    spark: SparkSession
    keys: list[str]
    sums: list[str]
    path: str = ""
    parts: list[tuple[int, str]] = field(default_factory=list)
    schema: object = None
    sizes: dict[str, int] = field(default_factory=dict)

    def __post_init__(self) -> None:
        self.path = self.path or fresh_dir(self.spark, "state")

    def snapshot(self) -> AdditiveState:
        """The state as it stands; what is added to either later isn't seen by the other."""
        return replace(self, path=fresh_dir(self.spark, "state"), parts=list(self.parts), sizes=dict(self.sizes))

    def add(self, version: int, rows: DataFrame) -> DataFrame:
        """Append what a delta adds, as the part of ``version``; returns it as written."""
        where = f"{self.path}/part-{version}-{uuid.uuid4().hex[:8]}"
        rows = rows.select(*self.keys, *self.sums)
        rows.write.parquet(where)
        self.schema = self.schema or rows.schema
        self.parts.append((version, where))
        return self.spark.read.schema(self.schema).parquet(where)

    def _bucket(self, keys: list[Column]) -> Column:
        return F.pmod(F.xxhash64(*keys), F.lit(BUCKETS)).cast("int")

    def read(self, touched: DataFrame | None = None, version: int | None = None) -> DataFrame:
        """Summed rows, of the ``touched`` keys (a row for each, any columns of the keys) if given."""
        found = [p for v, p in self.parts if version is None or v <= version]
        if not found:
            return self.spark.createDataFrame([], self.schema)
        plain = [p for p in found if "/buckets-" not in p]
        rows = self.spark.read.schema(self.schema).parquet(*plain) if plain else None
        for p in found:
            if p in plain:
                continue
            own = self.spark.read.schema(T.StructType([*self.schema.fields, T.StructField(BUCKET, T.IntegerType())])).parquet(p)
            lead = self._led_by(p)
            if touched is not None and set(lead) <= set(touched.columns):
                wanted = [r[0] for r in touched.select(self._bucket([F.col(c) for c in lead])).distinct().collect()]  # BUCKETS numbers at most
                own = own.where(F.col(BUCKET).isin(wanted))
            own = own.select(*self.keys, *self.sums)
            rows = own if rows is None else rows.unionByName(own)
        if touched is not None:
            match = None
            other = touched.select(*(F.col(c).alias(f"__t_{c}") for c in touched.columns))
            for c in touched.columns:
                one = F.col(c).eqNullSafe(F.col(f"__t_{c}"))
                match = one if match is None else match & one
            rows = rows.join(other, match, "left_semi") if match is not None else rows
        if len(found) < 2:
            return rows
        kinds = {f.name: f.dataType for f in self.schema}
        return rows.groupBy(*self.keys).agg(*(F.sum(c).cast(kinds[c]).alias(c) for c in self.sums))

    def _led_by(self, path: str) -> list[str]:
        """The keys by which a part in folders was split; its name has their positions."""
        return [self.keys[int(i)] for i in path.rsplit("-", 1)[1].split(".")]

    def compact(self, lead: list[str] | None = None) -> None:
        """Fold all parts into one; ``lead``: the keys by whose hash a large state is split into folders."""
        last = max(v for v, _ in self.parts)
        rows = self.read()
        live = F.lit(False)
        for c in self.sums:
            live = live | (F.col(c) != 0)
        rows = rows.where(live)
        if lead and self.bytes() >= LARGE:
            where = f"{self.path}/buckets-{last}-{uuid.uuid4().hex[:8]}-{'.'.join(str(self.keys.index(c)) for c in lead)}"
            split = rows.withColumn(BUCKET, self._bucket([F.col(c) for c in lead]))
            split.repartition(BUCKET).write.partitionBy(BUCKET).parquet(where)
        else:
            where = f"{self.path}/compact-{last}-{uuid.uuid4().hex[:8]}"
            rows.write.parquet(where)
        self.parts = [(last, where)]

    def tend(self, lead: list[str]) -> None:
        """Compact when there are many parts, or when the first part alone is large and not in folders yet."""
        if len(self.parts) >= MOST_PARTS or len(self.parts) == 1 and "/buckets-" not in self.parts[0][1] and self.bytes() >= LARGE:
            self.compact(lead)

    def bytes(self) -> int:
        """Size of its files; a part never changes, so each is asked for once."""
        jvm = self.spark.sparkContext._jvm
        for _, p in self.parts:
            if p not in self.sizes:
                path = jvm.org.apache.hadoop.fs.Path(p)
                self.sizes[p] = path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(path).getLength()
        return sum(self.sizes[p] for _, p in self.parts)
