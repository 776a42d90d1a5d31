"""A Bloom filter that stays: a table of 64-bit words, built, extended and probed by joins.

The table has as many rows as the filter has words, whatever the number of keys; a probe touches only the
words of the probing keys.  Deleted keys stay, which only lets needless rows pass.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class BloomIndex:
    words: DataFrame  # word, bits
    bits: int
    hashes: int

    @staticmethod
    def build(df: DataFrame, key: str | list[str], expected: int, bits_per_key: int = 10) -> BloomIndex:
        bits = max(64, 1 << math.ceil(math.log2(max(1, expected) * bits_per_key)))
        hashes = max(1, round(bits_per_key * math.log(2)))
        return BloomIndex(_words(df, key, bits, hashes), bits, hashes)

    def insert(self, df: DataFrame, key: str | list[str]) -> BloomIndex:
        both = self.words.unionByName(_words(df, key, self.bits, self.hashes))
        return replace(self, words=both.groupBy("word").agg(F.bit_or("bits").alias("bits")))

    def keep(self, df: DataFrame, key: str | list[str]) -> DataFrame:
        """The rows of ``df`` whose key (of one column or several) the filter may contain."""
        names = _listed(key)
        found = df.select(*(F.col(c).alias(f"__k{i}") for i, c in enumerate(names))).dropna().distinct()
        own = found.columns
        at = found.select(*own, F.explode(_positions(own, self.bits, self.hashes)).alias("p"))
        at = at.select(*own, F.shiftright("p", 6).alias("word"), F.col("p").bitwiseAND(F.lit(63)).cast("int").alias("bit"))
        hit = at.join(self.words, "word").where(F.getbit("bits", F.col("bit")) == 1).groupBy(*own).agg(F.count("*").alias("n"))
        passing = hit.where(F.col("n") == self.hashes).select(*(F.col(k).alias(c) for k, c in zip(own, names)))
        return df.join(passing, names, "left_semi")


def _listed(key: str | list[str]) -> list[str]:
    return [key] if isinstance(key, str) else list(key)


def _positions(key: list[str], bits: int, hashes: int) -> Column:
    """One position for each hash: an array of as many entries."""
    return F.array(*(F.pmod(F.xxhash64(F.lit(i), *key), F.lit(bits)) for i in range(hashes)))


def _words(df: DataFrame, key: str | list[str], bits: int, hashes: int) -> DataFrame:
    keys = df.select(*(F.col(c).alias(f"__k{i}") for i, c in enumerate(_listed(key)))).dropna().distinct()
    at = keys.select(F.explode(_positions(keys.columns, bits, hashes)).alias("p"))
    return at.groupBy(F.shiftright("p", 6).alias("word")).agg(F.expr("bit_or(shiftleft(1L, cast(p & 63 as int)))").alias("bits"))
