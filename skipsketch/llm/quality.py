"""Quality rules: base counts of each text, and perplexity under an n-gram model of its language.

The model predicts the characters of a word from the characters before them in the word.  Spark counts the
words of all documents by language, and from them the character n-grams; modified Kneser-Ney smoothing turns
the counts into probabilities, which are stored as sorted arrays of hashes with their values.  Scoring looks
up whole batches of words by binary search and remembers words.  A document's perplexity is that of the bytes
of its words; it is rejected beyond its language's bands, which lie ``WIDE`` interquartile ranges of the log
perplexity of that language above and below its quartiles.  Each distinct text counts once in the quartiles, so
that copies don't draw them together, and a range under ``LEAST`` counts as ``LEAST``.

Every n-gram counts at every size.  The number of n-grams follows the alphabet more than the corpus; they are
counted first, and up to ``ENTRIES`` the model is made on the driver and broadcast.  Above that the same
probabilities are made by joins: all scored words are counted, so that all their n-grams are in the model and
none is backed off; the words of each language are joined with their n-grams, and documents with their words.

Defined results: null or empty text has no words and fails the base rules; its perplexity is null.  A null
language is a language of its own.  Repeated rows are each returned.  Empty table: empty result.  Other
columns are ignored.
"""

from __future__ import annotations

import uuid
from collections import Counter, defaultdict
from collections.abc import Iterator
from functools import reduce
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skipsketch.llm.common import arrow_map, mixed, small, stored, values
from skipsketch.shipping import ship

ORDER, ENTRIES, WIDE = 4, 2_000_000, 2.0
#: Least interquartile range of log perplexity; at sf0.1 the four languages have 0.027 to 0.037.
LEAST = 0.02
START, END = "\x02", "\x03"
SYMBOLS = b"#*$%&|<>"
WHITE = b" \t\n\v\f\r"


class Vocabulary(dict):
    """word -> number in the order of first sight; ``logs`` has each language's log probabilities by number."""

    def __init__(self) -> None:
        super().__init__()
        self.words: list[bytes] = []
        self.logs: dict[str, np.ndarray] = {}

    def __missing__(self, word: bytes) -> int:
        self[word] = number = len(self.words)
        self.words.append(word)
        return number

    def numbers(self, texts: list[list[bytes]]) -> list[np.ndarray]:
        ends = np.cumsum([len(t) for t in texts])
        flat = np.fromiter(map(self.__getitem__, chain.from_iterable(texts)), np.int64, int(ends[-1]) if len(ends) else 0)
        return np.split(flat, ends[:-1]) if len(ends) else []

    def learn(self, model: Model, langs: list[str], numbers: list[np.ndarray]) -> None:
        """Score the words that are new in a language, together."""
        by: dict[str, list[np.ndarray]] = defaultdict(list)
        for lang, own in zip(langs, numbers):
            by[lang].append(own)
        for lang, own in by.items():
            logs = self.logs.get(lang, np.zeros(0, np.float64))
            if len(logs) < len(self.words):
                logs = np.concatenate((logs, np.full(len(self.words) + 50_000 - len(logs), np.nan)))
            every = np.concatenate(own)
            new = np.unique(every[np.isnan(logs[every])])
            if len(new):
                logs[new] = model.words(lang, [self.words[i].decode() for i in new])
            self.logs[lang] = logs


def base_counts(text: bytes, numbers: np.ndarray) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of a text; words are given by number, under 2 ** 31."""
    chars = len(text.translate(None, WHITE)) - int(np.count_nonzero((np.frombuffer(text, np.uint8) & 0xC0) == 0x80))
    lines: set[bytes] = set()
    again = 0
    for line in text.split(b"\n"):
        if line in lines:
            again += 1
        elif line.strip(WHITE):
            lines.add(line)
    repeat = 0
    if len(numbers) > 3:
        if int(numbers.max()) < 1 << 21:
            three = numbers[:-2] | numbers[1:-1] << 21 | numbers[2:] << 42
        else:  # pairs get numbers of their own first, so that no bit is lost
            pairs = np.unique(numbers[:-2] << 31 | numbers[1:-1], return_inverse=True)[1]
            three = pairs << 31 | numbers[2:]
        order = np.sort(three)
        twice = order[1:][order[1:] == order[:-1]]
        if len(twice):
            hit = np.flatnonzero(np.isin(three, twice))
            covered = np.zeros(len(numbers), bool)
            for i in range(3):
                covered[hit + i] = True
            repeat = int(covered.sum())
    return len(numbers), chars, len(text) - len(text.translate(None, SYMBOLS)), again, repeat


def word_counts(docs: DataFrame) -> DataFrame:
    """lang, word, n over all documents."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[str, Counter] = defaultdict(Counter)

        def flush() -> Iterator[pa.RecordBatch]:
            for lang, c in counts.items():
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(c), pa.string()), pa.array(c.keys(), pa.binary()).cast(pa.string()), pa.array(c.values(), pa.int64())], ["lang", "word", "n"])
            counts.clear()

        for batch in batches:
            for lang, text in zip(values(batch.column(0)), values(batch.column(1))):
                counts[lang].update(text.split())
            if sum(map(len, counts.values())) > 200_000:
                yield from flush()
        yield from flush()

    source = docs.select(F.coalesce(F.col("lang"), F.lit("")).alias("lang"), F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("text"))
    return source.mapInArrow(run, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))


def word_grams(words: DataFrame, order: int) -> DataFrame:
    """lang, word, n, gram: the n-gram that ends at each character of a word and at its end."""
    whole = words.select("lang", "word", "n", F.concat(F.lit(START), F.translate("word", START + END, ""), F.lit(END)).alias("w"))
    ends = F.sequence(F.lit(2), F.length("w"))
    return whole.select("lang", "word", "n", F.explode(F.transform(ends, lambda i: F.substring(F.col("w"), F.greatest(i - order + 1, F.lit(1)), F.least(i, F.lit(order))))).alias("gram"))


def ngram_counts(words: DataFrame, order: int = ORDER) -> DataFrame:
    """lang, gram, n: n-grams of the highest order, and shorter ones at the beginning of a word."""
    return word_grams(words, order).groupBy("lang", "gram").agg(F.sum("n").alias("n"))


def gathered(grams: DataFrame) -> list[tuple[str, str, int]]:
    """The counts on the driver."""
    return [(r[0], r[1], r[2]) for r in grams.toLocalIterator()]


def _cut(i: int) -> Column:
    """What is taken from n-grams seen ``i`` times (3: or more), from the counts of counts y1 to y4."""
    y = F.when(F.col("y1") > 0, F.col("y1") / (F.col("y1") + 2 * F.col("y2"))).otherwise(F.lit(0.5))
    now, then = F.col(f"y{i}"), F.col(f"y{i + 1}")
    return F.when(now > 0, F.least(F.greatest(i - (i + 1) * y * then / now, F.lit(0.05)), F.lit(i - 0.05))).otherwise(F.lit(0.5 * i))


def spread_model(grams: DataFrame, order: int) -> DataFrame:
    """lang, gram, logp of the n-grams that ``ngram_counts`` gives: the values of ``Model``, by joins."""
    tail = F.expr("substring(gram, 2)")
    levels = {}
    for k in range(order, 0, -1):
        levels[k] = grams.where(F.length("gram") == k)
        if k < order:  # an n-gram that begins a word is never the end of a longer one
            levels[k] = levels[k].union(levels[k + 1].groupBy("lang", tail.alias("gram")).agg(F.count("*").alias("n")))
        levels[k] = stored(levels[k], f"level-{k}")
    lower, made = None, []
    for k in range(1, order + 1):
        seen = [F.sum((F.col("n") == i).cast("long")).alias(f"y{i}") for i in (1, 2, 3, 4)]
        cuts = levels[k].groupBy("lang").agg(*seen, F.count("*").alias("alphabet")).select("lang", "alphabet", *(_cut(i).alias(f"c{i}") for i in (1, 2, 3)))
        cuts = stored(cuts, "cuts")
        cut = F.when(F.col("n") == 1, F.col("c1")).when(F.col("n") == 2, F.col("c2")).otherwise(F.col("c3"))
        rows = levels[k].join(small(cuts, cuts.count()), "lang").select("lang", "gram", "n", "alphabet", cut.alias("cut"), F.substring("gram", 1, k - 1).alias("context"), tail.alias("tail"))
        whole = rows.groupBy("lang", "context").agg(F.sum("n").alias("total"), F.sum("cut").alias("freed"))
        rows = rows.join(whole, ["lang", "context"])
        if lower is None:
            rows = rows.withColumn("under", 1 / (F.col("alphabet") + 1))
        else:
            rows = rows.join(lower.select("lang", F.col("gram").alias("tail"), F.col("p").alias("under")), ["lang", "tail"])
        p = (F.col("n") - F.col("cut")) / F.col("total") + F.col("freed") / F.col("total") * F.col("under")
        lower = stored(rows.select("lang", "gram", p.alias("p")), f"chances-{k}")
        made.append(lower)
    return reduce(DataFrame.union, made).where((F.length("gram") == order) | F.startswith("gram", F.lit(START))).select("lang", "gram", F.log("p").alias("logp"))


def spread_logs(docs: DataFrame, words: DataFrame, grams: DataFrame, order: int) -> DataFrame:
    """lang, key, log: the log probability of the words of all texts with that key together."""

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        langs, keys, found, n = [], [], [], []
        for lang, text in zip(values(batch.column(0)), values(batch.column(1))):
            own = Counter(text.split())
            langs += [lang] * len(own)
            keys += [xxhash.xxh3_128_digest(text)] * len(own)
            found += own.keys()
            n += own.values()
        return pa.RecordBatch.from_arrays([pa.array(langs, pa.string()), pa.array(keys, pa.binary()), pa.array(found, pa.binary()).cast(pa.string()), pa.array(n, pa.int64())], ["lang", "key", "word", "times"])

    model = spread_model(grams, order)
    logs = stored(word_grams(words, order).join(model, ["lang", "gram"]).groupBy("lang", "word").agg(F.sum("logp").alias("logp")), "word-logs")
    source = docs.select(F.coalesce(F.col("lang"), F.lit("")).alias("lang"), F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("text"))
    used = arrow_map(source, each, "lang string, key binary, word string, times long")
    return used.join(logs, ["lang", "word"]).groupBy("lang", "key").agg(F.sum(F.col("times") * F.col("logp")).alias("log"))


def code_points(texts: list[str]) -> np.ndarray:
    return np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32).astype(np.uint64)


def gram_hash(language: int, points: np.ndarray, width: int) -> np.ndarray:
    """Hash of the ``width`` code points that end at each place from width - 1 on."""
    n = len(points) - width + 1
    # a mixed seed: small ones would cancel against code points, and n-grams of different widths collide
    out = np.full(max(n, 0), mixed(np.array([language * 64 + width], np.uint64))[0], np.uint64)
    for i in range(width):
        out = mixed(out ^ points[i : n + i]) if n > 0 else out
    return out


class Model:
    """Interpolated modified Kneser-Ney: values by hash of n-gram, and back-off weights by hash of context."""

    def __init__(self, counts: list[tuple[str, str, int]], order: int = ORDER):
        self.order = order
        self.languages = {x: i for i, x in enumerate(sorted({c[0] for c in counts}))}
        self.floor = {}
        keys, vals, weights = [], [], []
        by: dict[str, dict[str, int]] = defaultdict(dict)
        for lang, gram, n in counts:
            by[lang][gram] = n
        for lang, found in by.items():
            levels: list[dict[str, int]] = [{} for _ in range(order + 1)]
            for gram, n in found.items():
                levels[len(gram)][gram] = n
            for k in range(order - 1, 0, -1):
                left = Counter(g[1:] for g in levels[k + 1])
                for g, n in left.items():
                    levels[k].setdefault(g, n)
            alphabet = max(1, len(levels[1]))
            self.floor[lang] = 1 / (alphabet + 1)
            held: list[dict[str, list[float]]] = [{} for _ in range(order + 1)]  # by width: log probability, log back-off weight
            lower: dict[str, float] = {}
            for k in range(1, order + 1):
                seen = Counter(min(n, 5) for n in levels[k].values())
                y = seen[1] / (seen[1] + 2 * seen[2]) if seen[1] else 0.5
                cut = [0.0, *(min(max(i - (i + 1) * y * seen[i + 1] / seen[i], 0.05), i - 0.05) if seen[i] else 0.5 * i for i in (1, 2, 3))]
                total: Counter = Counter()
                freed: dict[str, float] = defaultdict(float)
                for g, n in levels[k].items():
                    total[g[:-1]] += n
                    freed[g[:-1]] += cut[min(n, 3)]
                found_: dict[str, float] = {}
                for g, n in levels[k].items():
                    c = g[:-1]
                    under = lower.get(g[1:], self.floor[lang])
                    found_[g] = (n - cut[min(n, 3)]) / total[c] + freed[c] / total[c] * under
                    held[k][g] = [np.log(found_[g]), 0.0]
                for c in total:
                    w = np.log(freed[c] / total[c])
                    if c:
                        held[k - 1].setdefault(c, [np.nan, 0.0])[1] = w
                    else:
                        self.floor[lang] *= float(np.exp(w))  # the weight of the empty context
                lower = found_
            for k in range(1, order + 1):
                if held[k]:
                    keys.append(gram_hash(self.languages[lang], code_points(list(held[k])), k)[::k])
                    vals.append(np.array([v for v, _ in held[k].values()]))
                    weights.append(np.array([w for _, w in held[k].values()]))
        flat = np.concatenate(keys) if keys else np.zeros(1, np.uint64)
        by_key = np.argsort(flat)
        self.keys = flat[by_key]
        self.vals = (np.concatenate(vals) if vals else np.full(1, np.nan))[by_key]
        self.weights = (np.concatenate(weights) if weights else np.zeros(1))[by_key]
        # hashes are uniform, so their first bits say where in the sorted array to look
        self.bits = max(4, min(22, int(len(self.keys)).bit_length() + 3))
        heads = (self.keys >> np.uint64(64 - self.bits)).astype(np.int64)
        self.starts = np.searchsorted(heads, np.arange((1 << self.bits) + 1)).astype(np.int32)
        self.longest = int(np.diff(self.starts).max())

    def find(self, wanted: np.ndarray) -> np.ndarray:
        """Place of each hash in the arrays, -1 if it isn't there."""
        at = self.starts[(wanted >> np.uint64(64 - self.bits)).astype(np.int64)]
        out = np.full(len(wanted), -1, np.int32)
        for j in range(self.longest):
            place = np.minimum(at + j, len(self.keys) - 1)
            out = np.where(self.keys[place] == wanted, place, out)
        return out

    def words(self, lang: str, found: list[str]) -> np.ndarray:
        """Log probability of each word and its end."""
        if lang not in self.languages:
            return np.zeros(len(found))
        code = self.languages[lang]
        points = code_points([START + w.replace(START, "").replace(END, "") + END for w in found])
        start = points == ord(START)
        where = np.flatnonzero(start)
        place = np.arange(len(points)) - np.repeat(where, np.diff(np.append(where, len(points))))
        logp = np.full(len(points), np.log(self.floor[lang]))
        weight = np.zeros(len(points))  # of the context that ends at each place, one order lower
        for k in range(1, self.order + 1):
            at = self.find(gram_hash(code, points, k))  # of the n-gram that ends at k - 1, k, ...
            hit = at >= 0
            value = np.where(hit, self.vals[at], np.nan)
            inside = place[k - 1 :] >= k - 1
            if k > 1:
                before = np.concatenate(([0.0], weight[:-1]))
                logp += np.where(place >= k - 1, before, 0)
            known = inside & ~np.isnan(value)
            logp[k - 1 :][known] = value[known]
            weight = np.concatenate((np.zeros(k - 1), np.where(hit & inside, self.weights[at], 0)))
        logp[start] = 0
        return np.add.reduceat(logp, where)


_memory: dict[str, Vocabulary] = {}
#: Words that a worker remembers.
REMEMBERED = 400_000


def scored(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, lang, key (16 bytes of the text), the base counts, base_failed, size, log_perplexity (null without a model)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    tag = uuid.uuid4().hex
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, logs, keys, sizes = [], [], [], []
            for at in range(0, batch.num_rows, 500):
                texts = batch.column(2).slice(at, 500).to_pylist()
                langs = batch.column(1).slice(at, 500).to_pylist()
                if tag not in _memory or len(_memory[tag]) > REMEMBERED:
                    _memory.clear()
                    _memory[tag] = Vocabulary()
                words = _memory[tag]
                numbers = words.numbers([t.split() for t in texts])
                if shared.value is not None:
                    words.learn(shared.value, langs, numbers)
                for lang, text, own in zip(langs, texts, numbers):
                    rows.append(base_counts(text, own))
                    keys.append(xxhash.xxh3_128_digest(text))
                    sizes.append(len(text.translate(None, WHITE)) + len(own))
                    logs.append(-float(words.logs[lang][own].sum()) / sizes[-1] if len(own) and shared.value is not None else None)
            made = list(zip(*rows)) or [[]] * 5
            failed = [r[0] < 50 or 100 * r[4] > 50 * r[0] for r in rows]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(keys, pa.binary()), *(pa.array(x, pa.int64()) for x in made), pa.array(failed, pa.bool_()), pa.array(sizes, pa.int64()), pa.array(logs, pa.float64())], ["doc_id", "lang", "key", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "size", "log_perplexity"])

    source = docs.select("doc_id", F.coalesce(F.col("lang"), F.lit("")).alias("lang"), F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("text"))
    kind = docs.schema["doc_id"].dataType.simpleString()
    return source.mapInArrow(run, f"doc_id {kind}, lang string, key binary, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, size long, log_perplexity double")


def quality(docs: DataFrame, order: int = ORDER, wide: float = WIDE, most: int = ENTRIES) -> DataFrame:
    """doc_id, the base counts, base_failed, kept, perplexity: a row for each document."""
    words = word_counts(docs)
    grams = stored(ngram_counts(words, order), "ngrams")
    if grams.count() <= most:
        rows = scored(docs, Model(gathered(grams), order))
    else:
        logs = spread_logs(docs, stored(words, "words"), grams, order)
        rows = stored(scored(docs, None), "counted")
        copies = rows.groupBy("lang", "key").agg(F.count("*").alias("copies"))
        logs = logs.join(copies, ["lang", "key"]).select("lang", "key", (F.col("log") / F.col("copies")).alias("log"))
        rows = rows.join(logs, ["lang", "key"], "left").withColumn("log_perplexity", -F.col("log") / F.col("size")).drop("log")
    rows = stored(rows, "scored")
    usual = rows.where("not base_failed and log_perplexity is not null").groupBy("lang", "key").agg(F.min("log_perplexity").alias("log_perplexity"))
    usual = usual.groupBy("lang").agg(F.percentile_approx("log_perplexity", [0.25, 0.75], 10_000).alias("q"))
    low, high = F.element_at("q", 1), F.element_at("q", 2)
    reach = wide * F.greatest(high - low, F.lit(LEAST))
    usual = usual.select("lang", (low - reach).alias("low"), (high + reach).alias("high"))
    usual = stored(usual, "bands")
    usual = small(usual, usual.count())
    inside = F.coalesce(F.col("log_perplexity").between(F.col("low"), F.col("high")), F.lit(False))
    return rows.join(usual, "lang", "left").select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", (~F.col("base_failed") & inside).alias("kept"), F.exp("log_perplexity").alias("perplexity"))
