"""Line deduplication over a corpus by a deletion-neighbourhood join.

A line is compared by its words, lower-cased (A-Z only) and split at ASCII white space; a line without words
is never a duplicate.  Two lines are duplicates if their words are equal or, where both have ``min_words``
or more, if one word inserted, deleted or replaced makes them equal (edit distance 1 in words, whatever the
characters in that word).  A line goes if an earlier one, by (doc_id, line), is its duplicate.

The neighbourhood of a line is the hashes of all its variants with one word deleted.  Lines of equal length
are within the bound exactly if they share a variant with the deletion at one place; lines whose lengths
differ by one, if a variant of the longer is the shorter line.  So the earliest member of each key is a
partner of every other member and no pairs are listed.  Variants are made only for distinct lines that share
an exact half with another line, which any two lines within the bound do.

Defined results: null text is a document without lines.  Null doc_ids come last in the order.  Rows with one
doc_id and one text are one document, each returned.  Empty table: empty result.  Other columns are ignored.
A document that had words and lost all its lines has kept false, the others true.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skipsketch.llm.common import WordHash, arrow_map, mixed, stored, values

MIN_WORDS = 10
LAST = (1 << 63) - 1
PLACE = ["d", "t", "line"]

_hash = WordHash()


def words(line: bytes) -> list[bytes]:
    return line.lower().split()


def halves(found: list[bytes]) -> list[int]:
    """Hashes of the heads and tails, one of which any line within one edit shares; odd ones are of tails."""
    n = len(found)
    heads = {xxhash.xxh64_intdigest(b"h" + b" ".join(found[:t])) & ~1 for t in (n // 2, (n + 1) // 2)}
    tails = {xxhash.xxh64_intdigest(b"t" + b" ".join(found[n - t :])) | 1 for t in ((n - 1) // 2, n // 2)}
    return [x - (1 << 63) for x in heads | tails]


def variants(found: list[bytes], head: bool = True, tail: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the line without word i and the places i, last the hash of the whole line with -1.

    Where only the head is shared with other lines, words in it needn't be deleted, and likewise for the tail.
    """
    n = len(found)
    each = mixed(_hash.of(found))
    powers = np.cumprod(np.concatenate(([np.uint64(1)], np.full(n, np.uint64(0x9E3779B97F4A7C15)))))
    before = np.concatenate(([np.uint64(0)], np.cumsum(each * powers[:-1])))
    moved = np.concatenate(([np.uint64(0)], np.cumsum(each[1:] * powers[: n - 1])))
    places = np.arange(0 if tail else max(0, n // 2 - 1), n if head else min(n, (n + 1) // 2 + 2), dtype=np.int32)
    without = before[places] + (moved[-1] - moved[places])
    return mixed(np.append(without, before[-1])).view(np.int64), np.append(places, np.int32(-1))


def within_one(a: list[bytes], b: list[bytes]) -> bool:
    """Whether the edit distance of two word lists is at most 1."""
    if len(a) > len(b):
        a, b = b, a
    if len(b) - len(a) > 1:
        return False
    i = next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), len(a))
    return a[i + 1 :] == b[i + 1 :] if len(a) == len(b) else a[i:] == b[i + 1 :]


def _docs(docs: DataFrame) -> DataFrame:
    """d: doc_id, nulls last in the order; t: what tells apart rows that share it."""
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)).alias("d"), F.coalesce(F.xxhash64("text"), F.lit(0)).alias("t"), F.col("text").cast("binary").alias("text"))


def lines(docs: DataFrame, min_words: int) -> DataFrame:
    """d, t, line, key (16 bytes of its words), halves (of long enough lines): a row for each line with words."""

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        row, at, key, half = [], [], [], []
        for i, text in enumerate(values(batch.column(2))):
            for j, line in enumerate(text.split(b"\n") if text else []):
                if found := words(line):
                    row.append(i)
                    at.append(j)
                    key.append(xxhash.xxh3_128_digest(b" ".join(found)))
                    half.append(halves(found) if len(found) >= min_words else None)
        rows = pa.array(row, pa.int64())
        return pa.RecordBatch.from_arrays([batch.column(0).take(rows), batch.column(1).take(rows), pa.array(at, pa.int32()), pa.array(key, pa.binary()), pa.array(half, pa.list_(pa.int64()))], ["d", "t", "line", "key", "halves"])

    return arrow_map(_docs(docs), each, "d long, t long, line int, key binary, halves array<long>")


def texts_of(docs: DataFrame, places: DataFrame) -> DataFrame:
    """d, t, line, head, tail, text of the named lines; ``places`` has a row (d, t, line, side) for each shared half."""

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        row, at, head, tail, out = [], [], [], [], []
        for i, (text, wanted) in enumerate(zip(values(batch.column(2)), values(batch.column(3)))):
            found = text.split(b"\n")
            sides: dict[int, set[int]] = {}
            for x in wanted:
                sides.setdefault(x >> 1, set()).add(x & 1)
            for j, side in sides.items():
                row.append(i)
                at.append(j)
                head.append(0 in side)
                tail.append(1 in side)
                out.append(found[j])
        rows = pa.array(row, pa.int64())
        return pa.RecordBatch.from_arrays([batch.column(0).take(rows), batch.column(1).take(rows), pa.array(at, pa.int32()), pa.array(head, pa.bool_()), pa.array(tail, pa.bool_()), pa.array(out, pa.binary())], ["d", "t", "line", "head", "tail", "text"])

    wanted = places.groupBy("d", "t").agg(F.collect_set(F.col("line").cast("long") * 2 + F.col("side")).alias("wanted"))
    found = _docs(docs).join(wanted, ["d", "t"]).select("d", "t", "text", "wanted")
    return arrow_map(found, each, "d long, t long, line int, head boolean, tail boolean, text binary")


def neighbourhood(found: DataFrame) -> DataFrame:
    """key, gap (the deleted place, -1 of a whole line), d, t, line: a row for each variant."""

    def each(batch: pa.RecordBatch) -> pa.RecordBatch | None:
        if not batch.num_rows:
            return None
        made = [variants(words(text), head, tail) for text, head, tail in zip(*(values(batch.column(c)) for c in ("text", "head", "tail")))]
        row = pa.array(np.repeat(np.arange(len(made)), [len(k) for k, _ in made]))
        flat = [pa.array(np.concatenate(x)) for x in zip(*made)]
        return pa.RecordBatch.from_arrays([*flat, *(batch.column(c).take(row) for c in PLACE)], ["key", "gap", *PLACE])

    return arrow_map(found.select(*PLACE, "head", "tail", "text"), each, "key long, gap int, d long, t long, line int")


def near_earlier(found: DataFrame) -> DataFrame:
    """d, t, line of the lines in ``found`` (d, t, line, text) with an earlier one within the bound, verified."""
    rows = stored(neighbourhood(found), "variants")
    place = F.struct(*PLACE)
    first = rows.groupBy("key", "gap").agg(F.min(place).alias("first"), F.count("*").alias("m"))
    whole = F.when(F.col("gap") == -1, F.col("first"))
    part = F.when(F.col("gap") >= 0, F.col("first"))
    crossed = first.groupBy("key").agg(F.min(whole).alias("whole"), F.min(part).alias("part")).where("whole is not null and part is not null")
    same = rows.where("gap >= 0").join(first.where("m > 1 and gap >= 0").select("key", "gap", "first"), ["key", "gap"]).select(place.alias("a"), F.col("first").alias("b"))
    other = rows.join(crossed, "key").select(place.alias("a"), F.when(F.col("gap") == -1, F.col("part")).otherwise(F.col("whole")).alias("b"))
    best = same.union(other).where("b < a").groupBy("a").agg(F.min("b").alias("b"))

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        keep = [within_one(words(x), words(y)) for x, y in zip(values(batch.column(3)), values(batch.column(4)))]
        return batch.select(PLACE).filter(pa.array(keep, pa.bool_()))

    left = found.select(place.alias("a"), F.col("text").alias("x"))
    right = found.select(place.alias("b"), F.col("text").alias("y"))
    pairs = best.join(left, "a").join(right, "b").select(*(f"a.{c}" for c in PLACE), "x", "y")
    return arrow_map(pairs, each, "d long, t long, line int")


def removed_lines(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """d, t, line, near (whether it is only nearly equal to an earlier line) of every line to be removed."""
    every = stored(lines(docs, min_words), "lines")
    firsts = stored(every.groupBy("key").agg(F.min(F.struct(*PLACE, "halves")).alias("f")).select("key", "f.*"), "firsts")
    half = firsts.where("halves is not null").select(*PLACE, F.explode("halves").alias("half"))
    shared = half.groupBy("half").agg(F.count("*").alias("m")).where("m > 1").select("half")
    survivors = half.join(shared, "half").select(*PLACE, F.col("half").bitwiseAND(F.lit(1)).alias("side"))
    near = near_earlier(stored(texts_of(docs, survivors), "candidates")).select(*PLACE).distinct()
    copies = every.select("key", *PLACE).join(firsts.select("key", F.struct(*PLACE).alias("first")), "key").where(F.struct(*PLACE) != F.col("first")).select(*PLACE)
    return copies.withColumn("near", F.lit(False)).union(near.withColumn("near", F.lit(True)))


def dedup_lines(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """All columns of ``docs`` with text rewritten, and n_lines, n_removed, n_near, kept."""
    gone = removed_lines(docs, min_words).groupBy("d", "t").agg(F.collect_set("line").alias("gone"), F.sum(F.col("near").cast("long")).alias("near"))
    own = [c for c in docs.columns if c.lower() not in ("n_lines", "n_removed", "n_near", "kept")]
    keyed = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)).alias("d"), F.coalesce(F.xxhash64("text"), F.lit(0)).alias("t"), F.struct(*(F.col(f"`{c}`") for c in own)).alias("row"))
    joined = keyed.join(gone, ["d", "t"], "left").select("row", F.col("row.text").cast("binary").alias("text"), "gone", "near")

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts, total, cut, kept = [], [], [], []
        for text, drop in zip(values(batch.column(1)), values(batch.column(2))):
            found = text.split(b"\n") if text else []
            drop = set(drop or ())
            left = [x for j, x in enumerate(found) if j not in drop] if drop else found
            texts.append(text if not drop else b"\n".join(left))
            total.append(len(found))
            cut.append(len(drop))
            kept.append(not drop or any(x.split() for x in left))
        fields = batch.column(0)
        cols = [pa.array(texts, pa.binary()).cast(pa.string()) if c == "text" else fields.field(c) for c in own]
        near = batch.column(3).fill_null(0)
        return pa.RecordBatch.from_arrays([*cols, pa.array(total, pa.int64()), pa.array(cut, pa.int64()), near, pa.array(kept, pa.bool_())], [*own, "n_lines", "n_removed", "n_near", "kept"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*(F.col(f"`{c}`") for c in own)).schema), "n_lines long", "n_removed long", "n_near long", "kept boolean"])
    return arrow_map(joined, each, schema)


def oracle(min_words: int = MIN_WORDS) -> str:
    """The same in SQL, for documents with distinct doc_ids: all variants of all lines."""
    words = "regexp_extract_all(translate(line, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+')"
    return f"""
    WITH l AS (SELECT doc_id, line, j, doc_id * 1000000 + j AS o, {words} AS w
               FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS j FROM documents WHERE text <> '')),
    k AS (SELECT *, array_to_string(w, ' ') AS k FROM l WHERE len(w) > 0),
    f AS (SELECT k, min(o) AS o, any_value(w) AS w FROM k GROUP BY k),
    v AS (SELECT o, i, array_to_string(list_concat(w[1 : i - 1], w[i + 1 :]), ' ') AS d FROM (SELECT o, w, unnest(range(1, len(w) + 1)) AS i FROM f WHERE len(w) >= {min_words})),
    near AS (SELECT v.o FROM v JOIN (SELECT d, i, min(o) AS first FROM v GROUP BY d, i) USING (d, i) WHERE v.o > first
             UNION SELECT greatest(v.o, f.o) FROM v JOIN f ON v.d = f.k WHERE len(f.w) >= {min_words}),
    gone AS (SELECT k.o, false AS near FROM k JOIN f USING (k) WHERE k.o <> f.o UNION ALL SELECT o, true FROM near),
    per AS (SELECT doc_id, string_agg(line, chr(10) ORDER BY j) FILTER (gone.o IS NULL) AS text, count(*) AS n_lines, count(gone.o) AS n_removed,
                   count(*) FILTER (near) AS n_near, count(gone.o) = 0 OR count(*) FILTER (gone.o IS NULL AND len(w) > 0) > 0 AS kept
            FROM l LEFT JOIN gone ON gone.o = l.o GROUP BY doc_id)
    SELECT doc_id, CASE WHEN n_lines IS NULL THEN d.text ELSE coalesce(per.text, '') END AS text, coalesce(n_lines, 0)::BIGINT AS n_lines,
           coalesce(n_removed, 0)::BIGINT AS n_removed, coalesce(n_near, 0)::BIGINT AS n_near, coalesce(kept, true) AS kept
    FROM documents d LEFT JOIN per USING (doc_id)"""
