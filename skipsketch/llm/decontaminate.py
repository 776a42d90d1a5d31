"""Benchmark passages in documents: a prefix-filtered set join, by DataFrame functions only.

Words are runs of ASCII letters and digits and of non-ASCII characters, A-Z lower-cased.  Every item gives
windows of ``width`` consecutive words; a shorter item is one window.  A document holds a window if the
window's words occur in it consecutively, that is, at containment 1.  At that threshold the necessary prefix
of a window is its rarest word: words are ordered by their count over all documents, only the rarest is
joined with the documents' words, and the place of the word in the window gives the one start that is
possible.  Candidates whose start or end lies outside the document, or whose second rarest word is not at its
place, fall away before the exact comparison of the whole window.

Defined results: null text has no words.  Items without words give no window; a null item_id marks hits but
is not counted.  Repeated items are one.  Repeated rows of documents are each returned.  Empty tables: no
hits, or no rows.  Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skipsketch.llm.common import BROADCAST_ROWS, small, stored

#: What lies between words, and the letters that are lower-cased.
BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
WIDTH = 13
#: No word holds a space, so this one stands for the document itself.
DOCUMENT = " "


def split_words(text: Column) -> Column:
    """Words in their own case; the first and the last may be empty, as places of words don't depend on them."""
    # upper-case letters are separators in BETWEEN, as the words are those of the lower-cased text
    return F.split(F.coalesce(text, F.lit("")), r"[^0-9A-Za-z\x{80}-\x{10FFFF}]+", -1)


def n_words(words: Column) -> Column:
    empty = (F.element_at(words, 1) == "").cast("long") + ((F.size(words) > 1) & (F.element_at(words, -1) == "")).cast("long")
    return F.size(words) - empty


def windows(benchmark: DataFrame, width: int) -> DataFrame:
    """item_id, start, words (array) of each window; w is the window's number in its item."""
    text = F.translate("text", UPPER, LOWER)
    items = benchmark.select("item_id", F.filter(split_words(text), lambda w: w != "").alias("all")).where("size(all) > 0").distinct()
    starts = F.sequence(F.lit(0), F.greatest(F.size("all") - width, F.lit(0)))
    return items.select("item_id", "all", F.explode(starts).alias("start")).select("item_id", F.slice("all", F.col("start") + 1, width).alias("words"))


def word_counts(docs: DataFrame, wanted: DataFrame, n_wanted: int) -> DataFrame:
    """word, count: over all documents, of the wanted words."""
    words = docs.select(F.explode(split_words(F.col("text"))).alias("w")).select(F.lower("w").alias("word"))
    return words.join(small(wanted, n_wanted), "word").groupBy("word").agg(F.count("*").alias("count"))


def contained(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, most: int = BROADCAST_ROWS) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items (array of strings): a row for each row of ``docs``; up to ``most`` prefixes are broadcast."""
    wins = stored(windows(benchmark, width).groupBy("words").agg(F.collect_set("item_id").alias("items")).withColumn("id", F.xxhash64("words")), "windows")
    # lower() also maps letters that the rule keeps; it only widens the candidates, which are compared exactly below
    wanted = stored(wins.select(F.explode("words").alias("w")).select(F.lower("w").alias("word")).distinct(), "vocabulary")
    n_wanted = wanted.count()
    counts = small(stored(word_counts(docs, wanted, n_wanted), "counts"), n_wanted)
    placed = wins.select("words", "items", F.posexplode("words").alias("at", "w")).withColumn("word", F.lower("w"))
    placed = placed.join(counts, "word", "left").groupBy("words", "items").agg(F.array_sort(F.collect_list(F.struct(F.coalesce("count", F.lit(0)).alias("count"), "at", "word"))).alias("rare"))
    second = F.coalesce(F.try_element_at("rare", F.lit(2)), F.element_at("rare", 1))
    prefix = placed.select(F.element_at("rare", 1)["word"].alias("token"), F.element_at("rare", 1)["at"].alias("at"), second["at"].alias("at2"), second["word"].alias("word2"), F.size("words").alias("len"), F.array_join("words", " ").alias("window"), "items")
    own = docs.sparkSession.range(1).select(F.lit(DOCUMENT).alias("token"), F.lit(0).alias("at"), F.lit(0).alias("at2"), F.lit("").alias("word2"), F.lit(0).alias("len"), F.lit("").alias("window"), F.array().cast(prefix.schema["items"].dataType).alias("items"))
    prefix = stored(prefix.union(own), "prefixes")

    n_prefix = prefix.count()
    source = docs.select(F.col("doc_id"), F.xxhash64("text").alias("t"), split_words(F.col("text")).alias("words"))
    start = F.col("pos") - F.col("at")
    fits = (start >= 0) & (start + F.col("len") <= F.size("words"))
    near = F.lower(F.element_at("words", start + F.col("at2") + 1)) == F.col("word2")
    exact = F.translate(F.array_join(F.slice("words", start + 1, F.col("len")), " "), UPPER, LOWER) == F.col("window")
    hit = F.when(fits, F.when(near, exact).otherwise(False)).otherwise(False)
    span = F.struct(start.alias("s"), (start + F.col("len")).alias("e"))
    zero = F.struct(F.lit(0).alias("covered"), F.lit(0).alias("end"))
    covered = F.aggregate("spans", zero, lambda a, x: F.struct((a["covered"] + F.greatest(x["e"] - F.greatest(a["end"], x["s"]), F.lit(0))).alias("covered"), F.greatest(a["end"], x["e"]).alias("end")))["covered"]
    found = [F.array_sort(F.collect_set("span")).alias("spans"), F.array_distinct(F.flatten(F.collect_set("items"))).alias("items")]
    if n_prefix <= most:  # one pass: the prefixes go to the documents, and a token of its own stands for each document
        places = source.select("doc_id", "t", "words", n_words(F.col("words")).alias("n_words"), F.posexplode(F.concat("words", F.array(F.lit(DOCUMENT)))).alias("pos", "w"))
        hits = places.join(F.broadcast(prefix), F.lower("w") == F.col("token")).where((F.col("token") == DOCUMENT) | hit)
        hits = hits.select("doc_id", "t", "n_words", "items", F.when(F.col("token") != DOCUMENT, span).alias("span"))
        each = hits.groupBy("doc_id", "t").agg(F.max("n_words").alias("n_words"), F.count(F.when(F.col("span").isNull(), 1)).alias("copies"), *found)
    else:  # thin places meet the prefixes by word; only candidates get their words back
        base = source.select("doc_id", "t", n_words(F.col("words")).alias("n_words")).groupBy("doc_id", "t").agg(F.max("n_words").alias("n_words"), F.count("*").alias("copies"))
        texts = source.dropDuplicates(["doc_id", "t"])
        rare = prefix.where(F.col("token") != DOCUMENT)
        places = texts.select(F.col("doc_id").alias("d"), F.col("t").alias("h"), F.posexplode("words").alias("pos", "w")).select("d", "h", "pos", F.lower("w").alias("token"))
        candidates = places.join(rare, "token").where(start >= 0)
        met = candidates.join(texts, F.col("d").eqNullSafe(F.col("doc_id")) & F.col("h").eqNullSafe(F.col("t"))).where(hit)
        hits = met.select(F.col("d"), F.col("h"), "items", span.alias("span")).groupBy("d", "h").agg(*found)
        each = base.join(hits, F.col("doc_id").eqNullSafe(F.col("d")) & F.col("t").eqNullSafe(F.col("h")), "left")
        each = each.withColumn("spans", F.coalesce("spans", F.array().cast(hits.schema["spans"].dataType))).withColumn("items", F.coalesce("items", F.array().cast(hits.schema["items"].dataType)))
    each = each.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))))
    return each.select("doc_id", F.col("n_words").cast("long").alias("n_words"), covered.cast("long").alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.array_sort(F.transform("items", lambda x: x.cast("string"))).alias("items"), "t")


def decontaminate(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH) -> DataFrame:
    """``contained`` with items_sha256 and contaminated: a twentieth or more of the words lie in hits."""
    found = contained(docs, benchmark, width)
    return found.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), ((F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))).alias("contaminated"), "t")


def clean(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH) -> DataFrame:
    """The rows of ``docs`` that are not contaminated, with their columns."""
    bad = decontaminate(docs, benchmark, width).where("contaminated").select(F.col("doc_id").alias("__bad_doc"), F.col("t").alias("__bad_text")).distinct()
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"))  # whatever the columns' names
    kept = rows.join(bad, F.col("row.doc_id").eqNullSafe(F.col("__bad_doc")) & (F.xxhash64("row.text") == F.col("__bad_text")), "left_anti")
    return kept.select("row.*")


def oracle(width: int = WIDTH) -> str:
    """The same in SQL."""
    words = "regexp_extract_all(translate(coalesce(text, ''), '%s', '%s'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+')" % (UPPER, LOWER)
    return f"""
    WITH i AS (SELECT item_id, {words} AS w FROM benchmark),
    win AS (SELECT DISTINCT item_id, array_to_string(w[s + 1 : s + {width}], ' ') AS win, least(len(w), {width}) AS n
            FROM (SELECT item_id, w, unnest(range(0, greatest(len(w) - {width}, 0) + 1)) AS s FROM i WHERE len(w) > 0)),
    d AS (SELECT doc_id, {words} AS w FROM documents),
    lens AS (SELECT DISTINCT n FROM win),
    g AS (SELECT doc_id, s, n, array_to_string(w[s + 1 : s + n], ' ') AS win
          FROM (SELECT doc_id, w, n, unnest(range(0, len(w) - n + 1)) AS s FROM d, lens WHERE len(w) >= n)),
    h AS (SELECT doc_id, s, g.n, item_id FROM g JOIN win USING (win)),
    p AS (SELECT doc_id, count(DISTINCT q) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS q FROM h) GROUP BY 1),
    t AS (SELECT doc_id, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS items FROM h GROUP BY 1)
    SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
           sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
    FROM d LEFT JOIN p USING (doc_id) LEFT JOIN t USING (doc_id)"""
