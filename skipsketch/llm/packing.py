"""Hierarchical packing of whole documents into training sequences of several context sizes.

A document's ids are cut into pieces of the full length and one tail.  Tails are routed to tiers, each to the shortest
context size that holds it.  From the longest tier down, the pieces of a tier first fill gaps of windows that are
open, the tightest first, and then open windows of their own context size, longest pieces first.  A window that ends
exactly full is a sequence of its context size without padding.  Shorter windows with a gap are packed in turn, as
units, into gaps of the longest windows and into new ones.  Longest windows filled to ``fill`` or more are padded.
Pieces of emptier ones are cut at powers of two, each part a sequence of a shorter context size without padding.

The plan is made on the histogram of lengths, which has at most as many entries as the length of a sequence, whatever
the corpus; pieces then find their place by their rank within their length.  Ranks are counted over salted groups of
a length, as many as its own number of pieces asks for, so no length, however common, meets in one task.

Sequences of one kind have consecutive ids, and ``step`` deals them evenly over steps, so steps hold the context
sizes in equal shares.

Defined results: null text is empty; an empty document is one piece that holds the closing id alone.  Null
doc_ids and repeated rows are packed like any other; doc_ids are integers.  Empty table: empty result.  Other columns
are ignored.
"""

from __future__ import annotations

import json
import os
import struct
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from skipsketch.llm.common import arrow_map, stored, values

LENGTH, CLOSING, FILL, SALTED = 2048, 1, 0.97, 5_000
#: Context sizes, each half of the one before.
TIERS = 4
#: Fixed value: the public pattern by which this kind of vocabulary splits a text.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


class Encoder:
    """Texts to little-endian 32-bit ids by a byte-level BPE, as the definition's own library gives them.

    A special token's string inside a text is that token; none is added around a text.

    Where the order of the vocabulary is that of the merges, as in the public one, ranks say the same as the
    merges and the faster library that works on ranks serves; otherwise the definition's own library.
    """

    def __init__(self, definition: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        parts = json.loads(definition)
        split = parts["pre_tokenizer"] or {}
        self.ranked = None
        if split.get("type") == "ByteLevel" and split.get("use_regex", True) and not split.get("add_prefix_space") and not parts["normalizer"]:
            added = parts.get("added_tokens") or []
            if not any(t["lstrip"] or t["rstrip"] or t["single_word"] or t["normalized"] for t in added):
                self.ranked = self._by_rank(parts["model"], {t["content"]: t["id"] for t in added})
        if self.ranked is None:
            from tokenizers import Tokenizer

            self.tokenizer = Tokenizer.from_str(definition)

    @staticmethod
    def _by_rank(model: dict, special: dict[str, int]):  # noqa: ANN205
        import tiktoken

        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        hidden = [b for b in range(256) if b not in shown]
        byte = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}
        vocab = model["vocab"]
        merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        if any(vocab.get(a + b) != 256 + i for i, (a, b) in enumerate(merges)):
            return None
        ranks = {bytes(byte[c] for c in x): i for x, i in vocab.items() if i < 256 + len(merges)}
        own = tiktoken.Encoding("own", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens=special)
        return lambda text: own.encode(text, allowed_special="all") if any(x in text for x in special) else own.encode_ordinary(text)

    def __call__(self, text: str) -> bytes:
        ids = self.ranked(text) if self.ranked else self.tokenizer.encode(text, add_special_tokens=False).ids
        return np.array(ids, "<u4").tobytes()


_encoders: dict[int, Encoder] = {}


def powers(n: int) -> list[int]:
    """The powers of two that add up to n, largest first."""
    return [1 << i for i in range(n.bit_length() - 1, -1, -1) if n >> i & 1]


def pieces(docs: DataFrame, definition: str, length: int = LENGTH) -> DataFrame:
    """doc_id, start, length, crc, parts (crcs of its parts at powers of two, of tails), doc_tokens."""
    shared = docs.sparkSession.sparkContext.broadcast(definition)
    tag = hash((definition, length))

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        if tag not in _encoders:
            _encoders[tag] = Encoder(shared.value)
        encode = _encoders[tag]
        row, start, size, crc, parts, total = [], [], [], [], [], []
        for i, text in enumerate(values(batch.column(1))):
            ids = encode(text or "") + struct.pack("<I", CLOSING)
            n = len(ids) // 4
            for s in range(0, n, length):
                own = ids[4 * s : 4 * (s + length)]
                row.append(i)
                start.append(s)
                size.append(len(own) // 4)
                crc.append(zlib.crc32(own))
                total.append(n)
                cut, p = [], 0
                for x in powers(len(own) // 4) if len(own) < 4 * length else ():
                    cut.append(zlib.crc32(own[4 * p : 4 * (p + x)]))
                    p += x
                parts.append(cut)
        rows = pa.array(row, pa.int64())
        cols = [batch.column(0).take(rows), *(pa.array(x, pa.int64()) for x in (start, size, crc)), pa.array(parts, pa.list_(pa.int64())), pa.array(total, pa.int64())]
        return pa.RecordBatch.from_arrays(cols, ["doc_id", "start", "length", "crc", "parts", "doc_tokens"])

    return arrow_map(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), each, "doc_id long, start long, length long, crc long, parts array<long>, doc_tokens long")


class Windows:
    """Open windows by their gap: what each holds (pieces by length), how many such windows, their context size."""

    def __init__(self) -> None:
        self.by_gap: dict[int, list[tuple[Counter, int, int]]] = {}

    def add(self, gap: int, held: Counter, n: int, context: int) -> None:
        if n:
            self.by_gap.setdefault(gap, []).append((held, n, context))

    def fill(self, size: int, what: Counter, left: int) -> int:
        """Put units of a size into gaps, the tightest first; the number that found none."""
        for gap in sorted(g for g in self.by_gap if g >= size):
            while left and self.by_gap.get(gap):
                held, n, context = self.by_gap[gap].pop()
                each = gap // size
                used = min(n, left // each)
                self.add(gap - each * size, held + _times(what, each), used, context)
                left -= used * each
                n -= used
                if n and left:  # fewer than fill one window
                    self.add(gap - left * size, held + _times(what, left), 1, context)
                    n, left = n - 1, 0
                self.add(gap, held, n, context)
        return left

    def open(self, size: int, what: Counter, left: int, context: int) -> None:
        """New windows of a context size for units of a size."""
        each = context // size
        self.add(context - each * size, _times(what, each), left // each, context)
        if left % each:
            self.add(context - left % each * size, _times(what, left % each), 1, context)


def _times(what: Counter, n: int) -> Counter:
    return Counter({size: k * n for size, k in what.items()})


def plan(counts: dict[int, int], length: int = LENGTH, fill: float = FILL, tiers: int = TIERS) -> tuple[np.ndarray, int]:
    """From the number of pieces of each length, where each rank goes; and the number of sequences.

    The array has rows (piece length, first rank, pieces of this length in a sequence, their first offset, first
    sequence id, 1 if cut at powers of two, number of pieces, context size), by piece length and first rank.
    """
    contexts = [length >> i for i in range(tiers) if length >> i]
    routed: dict[int, list[int]] = {c: [] for c in contexts}
    for size in sorted((x for x in counts if x < length), reverse=True):
        routed[min(c for c in contexts if c >= size)].append(size)
    windows = Windows()
    for context in contexts:
        for size in routed[context]:
            one = Counter({size: 1})
            windows.open(size, one, windows.fill(size, one, counts[size]), context)
    # windows of shorter tiers that aren't full become units for the longest
    full, long, units = [], Windows(), []
    for gap, some in windows.by_gap.items():
        for held, n, context in some:
            if not gap:
                full.append((context, held, n))
            elif context == length:
                long.add(gap, held, n, context)
            else:
                units.append((context - gap, sorted(held.items(), reverse=True), n))
    for total, held, n in sorted(units, reverse=True):
        what = Counter(dict(held))
        long.open(total, what, long.fill(total, what, n), length)
    rows, used, seq, loose = [], dict.fromkeys(counts, 0), 0, Counter()
    if counts.get(length):
        rows.append((length, 0, 1, 0, 0, 0, counts[length], length))
        seq = counts[length]
    for gap, some in long.by_gap.items():
        for held, n, _ in some:
            if gap <= (1 - fill) * length:
                full.append((length, held, n))
            else:
                loose.update(_times(held, n))
    for context, held, n in sorted(full, key=lambda x: (-x[0], sorted(x[1].items()), x[2])):
        offset = 0
        for size, k in sorted(held.items(), reverse=True):
            rows.append((size, used[size], k, offset, seq, 0, k * n, context))
            used[size] += k * n
            offset += k * size
        seq += n
    for size, n in sorted(loose.items(), reverse=True):
        rows.append((size, used[size], 1, 0, seq, 1, n, 0))
        used[size] += n
        seq += n * size.bit_count()
    return np.array(sorted(rows), np.int64).reshape(-1, 8), seq


def packed(docs: DataFrame, definition: str, length: int = LENGTH, fill: float = FILL, step_size: int = 256, tiers: int = TIERS) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, context, step: a row for each piece."""
    every = stored(pieces(docs, definition, length), "pieces")
    total = {r["length"]: r["count"] for r in every.groupBy("length").count().collect()}  # at most ``length`` rows
    salts = docs.sparkSession.createDataFrame([(n, -(-k // SALTED)) for n, k in total.items()], "length long, salts long")
    salted = every.join(F.broadcast(salts), "length").withColumn("salt", F.pmod(F.xxhash64("doc_id", "start", "crc"), F.col("salts"))).drop("salts")
    counts = stored(salted.groupBy("length", "salt").count(), "lengths")
    before = F.coalesce(F.sum("count").over(Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = counts.select("length", "salt", before.alias("before"))
    table, sequences = plan(total, length, fill, tiers)
    steps = max(1, -(-sequences // step_size))
    keys = table[:, 0] * (1 << 42) + table[:, 1]
    rank = F.row_number().over(Window.partitionBy("length", "salt").orderBy("doc_id", "start", "crc")) - 1
    ranked = salted.withColumn("own", rank).join(offsets, ["length", "salt"]).select("doc_id", "start", "length", "crc", "parts", "doc_tokens", (F.col("own") + F.col("before")).cast("long").alias("rank"))

    def each(batch: pa.RecordBatch) -> pa.RecordBatch | None:
        if not batch.num_rows:
            return None
        start, size, crc, total_, rank_ = (batch.column(i).to_numpy(zero_copy_only=False) for i in (1, 2, 3, 5, 6))
        at = np.searchsorted(keys, size * (1 << 42) + rank_, "right") - 1
        _, first, k, offset, seq, cut, count, tier = table[at].T
        q = rank_ - first
        n_parts = np.where(cut == 1, np.array([int(x).bit_count() for x in size]), 1)
        row = np.repeat(np.arange(len(size)), n_parts)
        nth = np.arange(len(row)) - np.repeat(np.cumsum(n_parts) - n_parts, n_parts)
        out = [start[row], size[row], crc[row], total_[row], np.where(cut == 1, seq + q, seq + q // k)[row] + np.where(cut == 1, count, 0)[row] * nth, np.where(cut == 1, 0, offset + q % k * size)[row]]
        lists = batch.column(4).to_pylist()
        i = 0
        for r in np.flatnonzero(cut == 1):
            i = int(np.searchsorted(row, r))
            p = 0
            for j, (x, c) in enumerate(zip(powers(int(size[r])), lists[r])):
                out[0][i + j], out[1][i + j], out[2][i + j] = start[r] + p, x, c
                p += x
        context = np.where(cut[row] == 1, out[1], tier[row])
        cols = [batch.column(0).take(pa.array(row)), *map(pa.array, (*out, context, out[4] % steps))]
        return pa.RecordBatch.from_arrays(cols, ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "context", "step"])

    return arrow_map(ranked, each, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, context long, step long")


def definition_of(path: str) -> str:
    """The tokenizer's definition, read on the driver; executors get it from there."""
    with open(path, encoding="utf-8") as f:
        return f.read()
