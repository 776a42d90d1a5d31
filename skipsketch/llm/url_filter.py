"""URL filters: curated rules first, association rules for the rest, by DataFrame functions only.

A URL becomes a set of tokens: its scheme, its host and each end of it after a dot, the words of all labels,
the segments of its path without numbers, its query keys, and marks for features such as a port.  FP-growth mines frequent
combinations of tokens and the label of labelled URLs.  Rules that conclude ``block`` are kept if they have enough
support (a share of the examples, and a number of blocked ones), if their confidence is high and, at its lower limit by
the number of examples, above the share of blocked examples, and if no rule on fewer of their tokens is as confident.  The rules are matched by an
inverted index: each rule stands under its rarest token, a page's tokens meet the index, and the rule holds if
the page has all its tokens.

Labels come from the documents that URLs name by number: a labelled document that is toxic or of low quality
makes its URL a ``block``.

Defined results: a null URL, or one without ``://``, has empty host and path and is allowed unless a mined rule
fits.  Repeated rows are each returned.  Empty tables: no mined rules, or no rows.  Other columns are ignored.
"""

from __future__ import annotations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skipsketch.llm.common import small, stored

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: (host, path, verdict); the longest that fits wins.
RULES = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow")]
BLOCK = "label:block"


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(_rest(url), r"^([^/?#]*)", 1), UPPER, LOWER)


def _rest(url: Column) -> Column:
    """What follows the first ://; empty without it."""
    at = F.instr(url, "://")
    return F.coalesce(F.when(at > 0, F.substring(url, at + 3, F.length(url))), F.lit(""))


def path_of(url: Column) -> Column:
    return F.regexp_extract(_rest(url), r"^[^/?#]*([^?#]*)", 1)


def curated(host: Column, path: Column, rules: list[tuple[str, str, str]]) -> Column:
    """Struct of rule and verdict of the longest rule that fits, or null."""
    fits = [F.when(((host == h) | F.endswith(host, F.lit("." + h))) & F.startswith(path, F.lit(p)), F.struct(F.lit(h + p).alias("rule"), F.lit(v).alias("verdict"))) for h, p, v in sorted(rules, key=lambda x: (-len(x[0] + x[1]), x[0]))]
    return F.coalesce(*fits, F.lit(None).cast("struct<rule:string,verdict:string>"))


def tokens(host: Column, path: Column, url: Column) -> Column:
    """Distinct tokens of a URL; empty parts and numbers give none."""
    def marked(mark: str, parts: Column) -> Column:
        return F.transform(F.filter(parts, lambda x: (x != "") & ~x.rlike("^[0-9]+$")), lambda x: F.concat(F.lit(mark), x))

    labels = F.split(F.regexp_replace(host, ":[0-9]*$", ""), r"\.")
    ends = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    segments = F.transform(F.split(path, "/"), lambda s: F.regexp_replace(s, "[0-9]+", "0"))
    keys = F.transform(F.filter(F.split(F.regexp_extract(F.coalesce(url, F.lit("")), r"\?([^#]*)", 1), "&"), lambda x: x != ""), lambda x: F.concat(F.lit("key:"), F.substring_index(x, "=", 1)))
    scheme = F.array(F.concat(F.lit("scheme:"), F.substring_index(F.coalesce(url, F.lit("")), "://", 1)))
    port = F.when(host.rlike(":[0-9]+$"), F.array(F.lit("port:given"))).otherwise(F.array().cast("array<string>"))
    words = F.flatten(F.transform(labels, lambda x: F.split(x, "-")))
    return F.array_distinct(F.concat(marked("domain:", ends), marked("word:", words), marked("path:", segments), keys, F.when(F.instr(F.coalesce(url, F.lit("")), "://") > 0, scheme).otherwise(F.array().cast("array<string>")), port))


#: Blocked examples that a rule needs, and the normal quantile by which its confidence is lowered before it is compared.
LEAST, SURE = 20, 2.58


def lower_limit(share: Column, n: Column) -> Column:
    """Wilson's lower limit of a share that was seen in n examples."""
    z2 = SURE * SURE
    return (share + z2 / (2 * n) - SURE * F.sqrt(share * (1 - share) / n + z2 / (4 * n * n))) / (1 + z2 / n)


def mined(labelled: DataFrame, support: float, confidence: float, least: int = LEAST) -> DataFrame:
    """rule, antecedent, confidence, lift of rules for ``block``, from (tokens, block); none that a shorter rule makes needless."""
    examples = labelled.agg(F.count("*").alias("n"), F.coalesce(F.avg(F.col("block").cast("double")), F.lit(0.0)).alias("share")).first()
    if not examples["share"]:
        least = max(least, examples["n"] + 1)
    support = min(1.0, max(support, least / max(1, examples["n"])))
    baskets = labelled.select(F.when(F.col("block"), F.concat("tokens", F.array(F.lit(BLOCK)))).otherwise(F.col("tokens")).alias("items")).where("size(items) > 0")
    model = FPGrowth(itemsCol="items", minSupport=support, minConfidence=confidence, numPartitions=int(labelled.sparkSession.conf.get("spark.sql.shuffle.partitions"))).fit(baskets)
    found = model.associationRules.where(F.array_contains("consequent", BLOCK))
    seen = F.round(F.col("support") * examples["n"] / F.col("confidence"))
    found = found.where(lower_limit(F.col("confidence"), seen) > examples["share"])
    found = stored(found.select(F.array_sort("antecedent").alias("antecedent"), "confidence", "lift"), "rules")
    # every shorter rule stands under its first token and meets the rules that hold this token
    parts = found.where("size(antecedent) > 1").select("antecedent", "confidence", F.explode("antecedent").alias("token"))
    shorter = found.select(F.element_at("antecedent", 1).alias("token"), F.col("antecedent").alias("fewer"), F.col("confidence").alias("short"))
    covers = (F.size("fewer") < F.size("antecedent")) & (F.size(F.array_except("fewer", "antecedent")) == 0) & (F.col("short") >= F.col("confidence"))
    needless = parts.join(shorter, "token").where(covers).select("antecedent").distinct()
    return found.join(needless, "antecedent", "left_anti").select(F.array_join("antecedent", " & ").alias("mined_rule"), "antecedent", "confidence", "lift")


def matched(urls: DataFrame, rules: DataFrame) -> DataFrame:
    """key, and the most confident mined rule: ``urls`` has key and tokens."""
    flat = urls.select("key", "tokens", F.explode("tokens").alias("token"))
    spread = flat.groupBy("token").agg(F.count("*").alias("n"))
    each = rules.select("mined_rule", "antecedent", "confidence", F.explode("antecedent").alias("token")).join(spread, "token", "left")
    index = each.groupBy("mined_rule", "antecedent", "confidence").agg(F.min(F.struct(F.coalesce("n", F.lit(0)).alias("n"), "token")).alias("rare")).select("mined_rule", "antecedent", "confidence", F.col("rare.token").alias("token"))
    index = stored(index, "rule-index")
    hits = flat.join(small(index, index.count()), "token").where(F.size(F.array_except("antecedent", "tokens")) == 0)
    return hits.groupBy("key").agg(F.max(F.struct("confidence", "mined_rule")).alias("best"))


def labelled_urls(pages: DataFrame, labels: DataFrame) -> DataFrame:
    """url, block: URLs whose path names a labelled document by number."""
    number = F.regexp_extract(path_of(F.col("url")), r"/([0-9]{1,18})(?:[./]|$)", 1)
    named = pages.where("url is not null").select("url", number.alias("n")).select("url", F.expr("try_cast(nullif(n, '') as bigint)").alias("doc_id"))
    bad = labels.where("doc_id is not null").groupBy("doc_id").agg(F.max(F.coalesce((F.col("toxic") == 1) | (F.col("quality") == 0), F.lit(False))).alias("block"))
    return named.join(bad, "doc_id").select("url", "block").distinct()


def examples_of(pages: DataFrame, labels: DataFrame) -> DataFrame:
    """tokens, block, held_out (a fifth by a hash of the URL) of the labelled URLs."""
    url = F.col("url")
    held = F.crc32(url.cast("binary")) % 5 == 0
    return labelled_urls(pages, labels).select(tokens(host_of(url), path_of(url), url).alias("tokens"), "block", held.alias("held_out"))


def evaluated(pages: DataFrame, labels: DataFrame, support: float = 0.0005, confidence: float = 0.6, least: int = LEAST) -> DataFrame:
    """n, blocked, n_hit, n_right of held-out examples under rules mined on the others: precision is n_right / n_hit, the base rate blocked / n."""
    found = examples_of(pages, labels)
    rules = mined(found.where("not held_out"), support, confidence, least)
    held = found.where("held_out").withColumn("key", F.monotonically_increasing_id())
    held = stored(held, "held-out")
    hits = matched(held.select("key", "tokens"), rules).select("key", F.lit(True).alias("hit"))
    return held.join(hits, "key", "left").agg(F.count("*").alias("n"), F.count_if("block").alias("blocked"), F.count("hit").alias("n_hit"), F.count_if(F.col("hit") & F.col("block")).alias("n_right"))


def judged(pages: DataFrame, labels: DataFrame, rules: list[tuple[str, str, str]] = RULES, support: float = 0.0005, confidence: float = 0.6, least: int = LEAST) -> DataFrame:
    """page_id, host, path, rule, verdict, mined_rule, confidence: a row for each page."""
    host, path, url = host_of(F.col("url")), path_of(F.col("url")), F.col("url")
    found = mined(examples_of(pages, labels), support, confidence, least)
    parts = pages.select("page_id", F.coalesce(host, F.lit("")).alias("host"), F.coalesce(path, F.lit("")).alias("path"), "url")
    open_ = parts.where(curated(F.col("host"), F.col("path"), rules).isNull()).select("url", "host", "path").distinct()
    hits = matched(open_.select(F.col("url").alias("key"), tokens(F.col("host"), F.col("path"), F.col("url")).alias("tokens")), found)
    hits = hits.select(F.col("key").alias("url"), "best")
    all_ = parts.withColumn("own", curated(F.col("host"), F.col("path"), rules)).join(hits, "url", "left")
    verdict = F.coalesce(F.col("own.verdict"), F.when(F.col("best").isNotNull(), F.lit("block")), F.lit("allow"))
    return all_.select("page_id", "host", "path", F.col("own.rule").alias("rule"), verdict.alias("verdict"), F.when(F.col("own").isNull(), F.col("best.mined_rule")).alias("mined_rule"), F.when(F.col("own").isNull(), F.col("best.confidence")).alias("confidence"))
