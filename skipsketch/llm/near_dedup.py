"""Near-duplicate documents by HyperMinHash sketches.

Every distinct shingle set gets 256 registers.  A register holds the leading-zero count and the first
mantissa bits of the smallest hash of its bucket.  Buckets that a small set leaves empty take the smallest
value of a permutation of their own, so two registers agree with the Jaccard probability at every set size.
Registers are banded; sets that meet in a band are compared by the collision-corrected estimate of the
Jaccard similarity, and what may reach the threshold is confirmed on the full shingle sets.

No group is expanded into all its pairs.  Copies with equal sets collapse into one vertex first.  In each
band's bucket every member is then compared with one hub, the member that meets most others over all bands.
Confirmed links merge vertices into components.  Members of one bucket share its hub; those around a hub that
are still in different components are compared in blocks, by registers first and then on the full sets, and a
block yields no more links than join its components.

Defined results: null text, or no words: empty set, a component of its own, kept.  Null doc_id: the row is
not linked, component_id is null, kept is true.  Repeated rows: each is returned; equal texts have one
component; rows that share a doc_id are one vertex.  Empty table: empty result.  Other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skipsketch.llm.common import WordHash, arrow_map, mixed, runs, shingle_hashes, stored, values

REGISTERS, MANTISSA = 256, 10
#: Chance up to which a pair at the threshold may share no band.
MISSED = 1e-5
BITS = 64 - 8
#: Standard deviations by which an estimate may lie under the threshold.
SLACK = 5.0

_odd = mixed(np.arange(1, REGISTERS + 1, dtype=np.uint64)) | np.uint64(1)
_words = WordHash()


def tokens(text: bytes | None) -> list[bytes]:
    """Lower-cased (A-Z only) runs without ASCII white space, as UTF-8."""
    return text.lower().split() if text else []


def shingles(text: bytes | None, k: int) -> np.ndarray:
    return shingle_hashes(_words.of(tokens(text)), k)


def registers(found: np.ndarray) -> np.ndarray:
    """The HyperMinHash of sorted distinct hashes, as 256 16-bit registers."""
    bucket = (found >> np.uint64(BITS)).astype(np.int64)
    first = np.concatenate(([True], bucket[1:] != bucket[:-1]))  # sorted: the first of a bucket is its least
    least = np.zeros(REGISTERS, np.uint64)
    empty = np.ones(REGISTERS, bool)
    least[bucket[first]] = found[first] & np.uint64((1 << BITS) - 1)
    empty[bucket[first]] = False
    if empty.any():
        own = np.flatnonzero(empty)
        step = max(1, 1_000_000 // len(own))
        low = np.full(len(own), np.uint64((1 << 64) - 1))
        for at in range(0, len(found), step):
            low = np.minimum(low, (found[at : at + step, None] * _odd[own] ^ _odd[own] >> np.uint64(7)).min(axis=0))
        least[own] = low >> np.uint64(64 - BITS)
    part, power = np.frexp(least.astype(np.float64))
    mantissa = np.maximum(part * (2 << MANTISSA) - (1 << MANTISSA), 0).astype(np.int64) & ((1 << MANTISSA) - 1)
    return ((np.clip(BITS - power, 0, 63) << MANTISSA) | mantissa).astype(np.uint16)


def band_rows(threshold: float) -> int:
    """Registers of a band: as many as a pair at the threshold can have and still share a band, but for ``MISSED``."""
    return max((r for r in range(1, 33) if (1 - threshold**r) ** (REGISTERS // r) <= MISSED), default=1)


def bands(regs: np.ndarray, rows: int) -> np.ndarray:
    """A hash of each band of so many registers of a matrix of registers, a row for each sketch."""
    n = REGISTERS // rows
    out = np.broadcast_to(np.arange(n, dtype=np.uint64), (len(regs), n)).copy()
    used = regs[:, : rows * n].reshape(len(regs), n, rows).astype(np.uint64)
    for i in range(rows):
        out = mixed(out ^ (used[:, :, i] + np.uint64(1)))
    return out.view(np.int64)


#: Chance that two different minima fall on one register: sum over leading-zero counts c of 2^-2(c+1), times 2^-MANTISSA.
COLLISION = (1 / 3) * 2.0**-MANTISSA


def estimate(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Jaccard similarities of two matrices of registers (or of one with a row), corrected for registers that agree by chance."""
    share = (a == b).mean(axis=1)
    return np.clip((share - COLLISION) / (1 - COLLISION), 0, 1)


def lowest_estimate(threshold: float) -> float:
    return threshold - SLACK * (threshold * (1 - threshold) / REGISTERS) ** 0.5


def sketched(docs: DataFrame, k: int) -> DataFrame:
    """doc_id, n, key (16 bytes that stand for the set), regs (512 bytes); of an empty set key and regs are null."""

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        n, key, regs = [], [], []
        for text in values(batch.column(1)):
            found = shingles(text, k)
            n.append(len(found))
            key.append(xxhash.xxh3_128_digest(found.tobytes()) if len(found) else None)
            regs.append(registers(found).tobytes() if len(found) else None)
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(key, pa.binary()), pa.array(regs, pa.binary())], ["doc_id", "n", "key", "regs"])

    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    return arrow_map(source, each, "doc_id long, n long, key binary, regs binary")


def _matrix(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint16).reshape(len(column), REGISTERS)


def banded(reps: DataFrame, rows: int) -> DataFrame:
    """band (hash), v: a row for each band of each vertex."""

    def each(batch: pa.RecordBatch) -> pa.RecordBatch | None:
        if not batch.num_rows:
            return None
        v = batch.column(0).to_numpy(zero_copy_only=False)
        return pa.RecordBatch.from_arrays([pa.array(bands(_matrix(batch.column(1)), rows).ravel()), pa.array(np.repeat(v, REGISTERS // rows))], ["band", "v"])

    return arrow_map(reps.select("v", "regs"), each, "band long, v long")


def confirmed(pairs: DataFrame, docs: DataFrame, k: int, percent: int) -> DataFrame:
    """Of the pairs (a, b) of doc_ids, those whose full sets meet the threshold."""

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        keep, last, right = [], None, None
        for x, y in zip(values(batch.column(2)), values(batch.column(3))):
            left = shingles(x, k)
            if y != last or right is None:
                last, right = y, shingles(y, k)
            common = len(np.intersect1d(left, right, assume_unique=True))
            keep.append(len(left) > 0 and 100 * common >= percent * (len(left) + len(right) - common))
        return batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    texts = docs.select(F.col("doc_id").cast("long").alias("a"), F.col("text").cast("binary").alias("x"))
    both = pairs.join(texts, "a").join(texts.select(F.col("a").alias("b"), F.col("x").alias("y")), "b").select("a", "b", "x", "y")
    return arrow_map(both, each, "a long, b long")


#: Members of a hub's group that are compared with each other at once.
BLOCK = 256


def dealt(members: DataFrame, sizes: DataFrame) -> DataFrame:
    """Members (hub, v, comp, ...) of the groups in ``sizes`` (hub, most, m, u) with i, j: blocks whose members are to be compared.

    ``most`` is the component of most of a group's m members, u is the number of the others.  Only pairs with one of the
    others can join components, so blocks i of those meet blocks j of all; members of ``most`` don't meet each other.
    """
    own = members.join(sizes, "hub").withColumn("ni", F.ceil(F.col("u") / BLOCK)).withColumn("nj", F.ceil(F.col("m") / BLOCK))
    i, j = F.pmod(F.xxhash64("v"), F.col("ni")), F.pmod(F.xxhash64("v", F.lit(1)), F.col("nj"))

    def through(n: str) -> Column:
        return F.explode(F.sequence(F.lit(0).cast("long"), F.col(n) - 1))

    right = own.select(*members.columns, through("ni").alias("i"), j.alias("j"))
    left = own.where("comp <> most").withColumn("own", j).select(*members.columns, i.alias("i"), through("nj").alias("j"), "own").where("j <> own").drop("own")
    return right.union(left)


def together(rows: DataFrame) -> DataFrame:
    """Rows of one (hub, i, j) side by side, as ``runs`` needs them."""
    return rows.repartition("hub", "i", "j").sortWithinPartitions("hub", "i", "j", "v")


def hopeful(members: DataFrame, least: float, percent: int) -> DataFrame:
    """hub, i, j, v, comp, own: members that some other in their blocks may be linked with across components, by their registers."""

    def run(batches):  # noqa: ANN001, ANN202
        for group in runs(batches, ["hub", "i", "j"]):
            if group.num_rows < 2:
                continue
            n, comp = (group.column(c).to_numpy() for c in ("n", "comp"))
            regs = _matrix(group.column("regs").combine_chunks())
            keep = np.zeros(group.num_rows, bool)
            for x in range(group.num_rows):
                y = np.flatnonzero((comp != comp[x]) & (np.minimum(n, n[x]) * 100 >= np.maximum(n, n[x]) * percent))
                if len(y) and not (keep[x] and keep[y].all()):
                    near = y[estimate(regs[y], regs[x]) >= least]
                    keep[near] = True
                    keep[x] |= len(near) > 0
            if keep.any():
                yield from group.filter(pa.array(keep)).select(["hub", "i", "j", "v", "comp"]).to_batches()

    return together(members).mapInArrow(run, "hub long, i long, j long, v long, comp long")


def crossing_links(rows: DataFrame, docs: DataFrame, k: int, percent: int) -> DataFrame:
    """a, b: links on full sets between components, as many as join what the blocks of ``rows`` link."""

    def run(batches):  # noqa: ANN001, ANN202
        for group in runs(batches, ["hub", "i", "j"]):
            v, comp = (group.column(c).to_numpy() for c in ("v", "comp"))
            sets = [shingles(x, k) for x in values(group.column("text").combine_chunks())]
            sizes = np.array([len(x) for x in sets])
            if group.num_rows < 2 or not sizes.all():
                continue
            ids = np.unique(np.concatenate(sets), return_inverse=True)[1]
            ends = np.cumsum(sizes)
            root = {c: c for c in comp.tolist()}

            def top(c: int) -> int:
                while root[c] != c:
                    c = root[c]
                return c

            a, b = [], []
            mark = np.zeros(ids.max() + 1, np.int32)
            for x in range(len(sets)):
                own = ids[ends[x] - sizes[x] : ends[x]]
                mark[own] = 1
                common = np.add.reduceat(mark[ids], ends - sizes)
                mark[own] = 0
                for y in np.flatnonzero((100 * common >= percent * (sizes + sizes[x] - common)) & (comp != comp[x])):
                    one, two = top(int(comp[x])), top(int(comp[y]))
                    if one != two:
                        root[max(one, two)] = min(one, two)
                        a.append(v[x])
                        b.append(v[y])
            if a:
                yield pa.RecordBatch.from_arrays([pa.array(np.array(a)), pa.array(np.array(b))], ["a", "b"])

    texts = docs.select(F.col("doc_id").cast("long").alias("v"), F.col("text").cast("binary").alias("text"))
    return together(rows.join(texts, "v").select("hub", "i", "j", "v", "comp", "text")).mapInArrow(run, "a long, b long")


def components(links: DataFrame) -> DataFrame:
    """v, comp (least vertex reachable) of every vertex in ``links`` (a, b); rounds grow as the log of a chain's length."""
    both = stored(links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "links")
    labels = stored(both.groupBy(F.col("a").alias("v")).agg(F.least(F.min("b"), F.first("a")).alias("comp")), "labels")
    while True:
        near = both.join(labels, both.b == labels.v).groupBy(F.col("a").alias("v")).agg(F.min("comp").alias("low"))
        lower = labels.join(near, "v").select("v", F.col("comp").alias("old"), F.least("comp", "low").alias("comp"))
        up = lower.select(F.col("v").alias("comp"), F.col("comp").alias("top"))
        new = stored(lower.join(up, "comp", "left").select("v", F.least("comp", F.coalesce("top", "comp")).alias("comp"), "old"), "labels")
        if new.where("comp <> old").isEmpty():
            return new.select("v", "comp")
        labels = new.select("v", "comp")


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id, kept: a row for each row of ``docs`` (doc_id, text); see the module."""
    threshold = percent / 100
    least = lowest_estimate(threshold)
    sketches = stored(sketched(docs, k), "sketches")
    usable = sketches.where("key is not null and doc_id is not null")
    groups = usable.groupBy("key").agg(F.min("doc_id").alias("doc_id"))
    reps = stored(usable.join(groups, ["key", "doc_id"]).dropDuplicates(["key", "doc_id"]).select(F.col("doc_id").alias("v"), "n", "regs"), "vertices")

    rows = banded(reps, band_rows(threshold))
    full = rows.groupBy("band").agg(F.count("*").alias("m")).where("m > 1")
    met = stored(rows.join(full, "band"), "met")
    degree = met.groupBy("v").agg(F.sum("m").alias("degree"))
    ranked = met.select("band", "v").join(degree, "v")
    hubs = ranked.groupBy("band").agg(F.min(F.struct((-F.col("degree")).alias("d"), "v")).alias("top")).select("band", F.col("top.v").alias("hub"))

    def scored(batch: pa.RecordBatch) -> pa.RecordBatch | None:
        if not batch.num_rows:
            return None
        value = estimate(_matrix(batch.column(2)), _matrix(batch.column(3)))
        keep = value >= least
        return pa.RecordBatch.from_arrays([pa.array(batch.column(i).to_numpy(zero_copy_only=False)[keep]) for i in (0, 1)] + [pa.array(value[keep])], ["a", "b", "value"])

    def scored_pairs(pairs: DataFrame) -> DataFrame:
        left = reps.select(F.col("v").alias("a"), F.col("regs").alias("x"))
        right = reps.select(F.col("v").alias("b"), F.col("regs").alias("y"))
        return arrow_map(pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y"), scored, "a long, b long, value double")

    around = stored(met.join(hubs, "band").where("v <> hub").select("v", "hub").distinct(), "around")
    starred = stored(scored_pairs(around.select(F.col("v").alias("a"), F.col("hub").alias("b"))), "starred")
    best = starred.groupBy("a").agg(F.max(F.struct("value", (-F.col("b")).alias("b"))).alias("t")).select("a", (-F.col("t.b")).alias("b"))
    links = stored(confirmed(best, docs, k, percent), "confirmed")
    comps = components(links)

    def label(v: str, name: str) -> Column:
        return F.coalesce(F.col(name), F.col(v))

    def labelled(rows: DataFrame, v: str) -> DataFrame:
        known = comps.select(F.col("v").alias(v), "comp")
        return rows.join(known, v, "left").select(*rows.columns, label(v, "comp").alias("comp"))

    # what may still join two components: the other pairs with a hub ...
    rest = starred.select("a", "b").join(best, ["a", "b"], "left_anti")
    rest = labelled(labelled(rest, "a").withColumnRenamed("comp", "ca"), "b").where("ca <> comp").select("a", "b")
    more = stored(confirmed(rest, docs, k, percent), "confirmed")
    comps = components(links.union(more)) if not more.isEmpty() else comps
    # ... and members that share a hub
    members = labelled(around, "v")
    shares = members.groupBy("hub", "comp").agg(F.count("*").alias("n"))
    mixed_hubs = shares.groupBy("hub").agg(F.max(F.struct("n", "comp")).alias("top"), F.sum("n").alias("m")).where("top.n < m")
    mixed_hubs = stored(mixed_hubs.select("hub", F.col("top.comp").alias("most"), "m", (F.col("m") - F.col("top.n")).alias("u")), "hubs")  # a plain table, so that the join below may split a large hub
    blocks = dealt(members, mixed_hubs).join(reps.select("v", "n", "regs"), "v").select("hub", "i", "j", "v", "comp", "n", "regs")
    inner = stored(crossing_links(hopeful(blocks, least, percent), docs, k, percent), "crossing")
    comps = components(links.union(more).union(inner)) if not inner.isEmpty() else comps

    group = usable.groupBy("key").agg(F.min("doc_id").alias("v")).join(comps, "v", "left").select("key", label("v", "comp").alias("comp"))
    # rows without a set have no partner; a key of their own keeps them from meeting in one task
    alone = F.concat(F.lit(b"-"), F.encode(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), "UTF-8"))
    return sketches.select("doc_id", "n", F.coalesce("key", alone).alias("key")).join(group, "key", "left").select(
        "doc_id",
        F.col("n").alias("n_shingles"),
        F.when(F.col("doc_id").isNotNull(), F.coalesce("comp", "doc_id")).alias("component_id"),
        F.coalesce(F.coalesce("comp", "doc_id") == F.col("doc_id"), F.lit(True)).alias("kept"),
    )


def oracle(k: int, percent: int) -> str:
    """The same in SQL, by all shared shingles and a recursive walk."""
    words = "regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+')"
    return f"""
    WITH RECURSIVE w AS (SELECT doc_id, {words} AS w FROM documents),
    s AS (SELECT DISTINCT doc_id, array_to_string(w[i : i + {k - 1}], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - {k - 1}, 1) + 1)) AS i FROM w WHERE len(w) > 0)),
    n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
    p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS m FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
    l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * m >= {percent} * (x.n + y.n - m)),
    c AS (SELECT doc_id AS v, doc_id AS r FROM w UNION SELECT l.b, c.r FROM c JOIN l ON l.a = c.v AND c.r <= l.b),
    least_ AS (SELECT v, min(r) AS r FROM c GROUP BY v)
    SELECT doc_id, coalesce(n, 0)::BIGINT AS n_shingles, r AS component_id, r = doc_id AS kept FROM w LEFT JOIN n USING (doc_id) JOIN least_ ON v = doc_id"""
