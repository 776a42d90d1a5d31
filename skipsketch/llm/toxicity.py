"""Toxicity by weak supervision.

Voters are lexicon words and patterns (word beginnings of 4 to 6 letters), chosen from labelled training rows
by how surely they mark a toxic text, plus one pattern voter for texts without any of them.  A generative label
model is fitted by expectation maximisation: each voter has a rate of voting in toxic and in clean texts, and
voters that agree beyond what the class explains share their weight, so that a word and its beginnings count
about once.  Its posterior labels train a linear classifier over the same kinds of features.

Training rows are a bounded sample (``SAMPLE`` labelled rows, least hash first) of those whose crc32 of doc_id
as text leaves a remainder other than 0 by 5.  Labels, lang, source and doc_id are never inputs of a score.

Defined results: null or empty text has the score of a text without features.  A null doc_id is not held out
and never trains.  A doc_id labelled twice is toxic if one label says so; null labels are ignored.  With no
usable label every score is 0.  Repeated rows are each returned.  Other columns are ignored.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skipsketch.llm.common import arrow_map, stored, values

#: Labelled documents to learn from; voters and features are all that these give evidence for.
SAMPLE = 20_000
#: Least evidence for a feature: log-likelihood ratio of its toxic share against the share in all texts.
EVIDENCE = 9.0
BEGINNINGS = (4, 5, 6)
_word = re.compile(r"[^\W\d_]+")


def held_out() -> Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False))


def features(text: str | None) -> set[str]:
    """Distinct words, and beginnings marked by a closing hyphen."""
    found = set(_word.findall(text.lower())) if text else set()
    return found | {w[:n] + "-" for w in found for n in BEGINNINGS if len(w) > n}


def sample(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> DataFrame:
    """text, toxic: training rows."""
    known = labels.where("toxic is not null and doc_id is not null").where(~held_out()).groupBy("doc_id").agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    known = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    found = docs.select("doc_id", "text").join(F.broadcast(known), "doc_id")  # at most ``most`` rows are broadcast
    # a document that stands there more than once is one of the sample
    return found.groupBy("doc_id").agg(F.max_by(F.struct("text", "toxic"), F.struct(F.xxhash64("text"), "text")).alias("row")).select("row.text", "row.toxic")


def marked(rows: DataFrame) -> list[tuple[str, int, int]]:
    """Of the sample: features that mark toxic texts, with their toxic and their whole count."""

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        counts: dict[str, list[int]] = {}
        for text, toxic in zip(values(batch.column(0)), values(batch.column(1))):
            for x in features(text):
                c = counts.setdefault(x, [0, 0])
                c[0] += toxic
                c[1] += 1
        return pa.RecordBatch.from_arrays([pa.array(counts.keys(), pa.string()), pa.array([c[0] for c in counts.values()], pa.int64()), pa.array([c[1] for c in counts.values()], pa.int64())], ["feature", "toxic", "n"])

    found = arrow_map(rows, each, "feature string, toxic long, n long").groupBy("feature").agg(F.sum("toxic").alias("toxic"), F.sum("n").alias("n"))
    total = rows.agg(F.sum("toxic").alias("toxic"), F.count("*").alias("n")).first()
    base = min(max((total["toxic"] or 0) / max(1, total["n"]), 1e-4), 0.5)
    share = F.col("toxic") / F.col("n")
    evidence = F.col("toxic") * F.log(share / base) + (F.col("n") - F.col("toxic")) * F.log(F.greatest(1 - share, F.lit(1e-9)) / (1 - base))
    top = found.where(F.col("toxic") >= 0.85 * F.col("n")).where(evidence >= EVIDENCE).orderBy(F.desc("toxic"), "n", "feature")
    return [tuple(r) for r in top.collect()]


@dataclass
class LabelModel:
    """Rates of each voter in both classes, the share of toxic texts, and the weights that correlations leave."""

    prior: float = 0.1
    toxic: np.ndarray = field(default_factory=lambda: np.zeros(0))
    clean: np.ndarray = field(default_factory=lambda: np.zeros(0))
    weight: np.ndarray = field(default_factory=lambda: np.zeros(0))

    def posterior(self, votes: np.ndarray) -> np.ndarray:
        yes = np.log(self.toxic / self.clean) * self.weight
        no = np.log((1 - self.toxic) / (1 - self.clean)) * self.weight
        logit = np.log(self.prior / (1 - self.prior)) + _times(votes, yes - no) + no.sum()
        return 1 / (1 + np.exp(-np.clip(logit, -30, 30)))

    def fit(self, votes: np.ndarray, rounds: int = 12) -> np.ndarray:
        """Posterior labels of a boolean matrix of votes, a column for each voter; the last column votes for clean."""
        p = np.where(votes[:, :-1].any(axis=1), 0.9, 0.05)
        n = len(votes)
        for _ in range(rounds):
            self.prior = float(np.clip(p.mean(), 1e-3, 1 - 1e-3))
            self.toxic = (_times(votes.T, p) + 0.5) / (p.sum() + 1)
            self.clean = (_times(votes.T, 1 - p) + 0.05) / ((1 - p).sum() + 1)
            # what voters share beyond the class, summed over a few documents at a time
            both = np.zeros((votes.shape[1],) * 2)
            for at in range(0, n, CHUNK):
                q = p[at : at + CHUNK]
                rest = votes[at : at + CHUNK] - np.outer(q, self.toxic) - np.outer(1 - q, self.clean)
                both += rest.T @ rest
            both /= n
            spread = np.sqrt(np.maximum(np.diag(both), 1e-9))
            tied = np.clip(both / np.outer(spread, spread), 0, 1)
            np.fill_diagonal(tied, 0)
            tied[tied < 0.1] = 0
            self.weight = 1 / (1 + tied.sum(axis=1))
            p = self.posterior(votes)
        return p


#: Documents whose votes are numbers in memory at once.
CHUNK = 2_000


def _times(votes: np.ndarray, by: np.ndarray) -> np.ndarray:
    """The product of a matrix of votes with a vector, a few rows at a time."""
    return np.concatenate([votes[at : at + CHUNK].astype(float) @ by for at in range(0, len(votes), CHUNK)]) if len(votes) else np.zeros(0)


def linear(rows: np.ndarray, cols: np.ndarray, goal: np.ndarray, width: int, rounds: int = 300, ridge: float = 1e-4) -> tuple[np.ndarray, float]:
    """Logistic regression on sparse presence features towards labels between 0 and 1."""
    w, bias, n = np.zeros(width), -2.0, max(1, len(goal))
    seen_w, seen_b = w.copy(), bias
    step = 4.0 * n / max(1.0, float(np.bincount(cols, minlength=width).max(initial=1)))
    step = min(step, 40.0)
    for t in range(1, rounds + 1):
        z = np.bincount(rows, seen_w[cols], n) + seen_b
        g = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - goal
        new_w = seen_w - step * (np.bincount(cols, g[rows], width) / n + ridge * seen_w)
        new_b = seen_b - min(step, 4.0) * g.mean()
        seen_w, seen_b = new_w + (t - 1) / (t + 2) * (new_w - w), new_b + (t - 1) / (t + 2) * (new_b - bias)
        w, bias = new_w, new_b
    return w, float(bias)


def fit(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> tuple[dict[str, float], float, LabelModel]:
    """Weights by feature, the bias, and the label model; no features at all if no label can be used."""
    rows = stored(sample(docs, labels, most), "sample")
    chosen = marked(rows)
    number = {x: i for i, (x, _, _) in enumerate(chosen)}
    if not number:
        return {}, float("-inf"), LabelModel()

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        found = [sorted(number[x] for x in features(t) if x in number) for t in batch.column(0).to_pylist()]
        return pa.RecordBatch.from_arrays([pa.array(found, pa.list_(pa.int32()))], ["found"])

    held = [r[0] for r in arrow_map(rows, each, "found array<int>").collect()]  # at most ``most`` rows, with the numbers of their features
    n = len(held)
    at = np.repeat(np.arange(n), [len(x) for x in held]).astype(np.int64)
    cols = np.concatenate([np.asarray(x, np.int64) for x in held]) if n else np.zeros(0, np.int64)
    votes = np.zeros((n, len(chosen) + 1), bool)
    votes[at, cols] = True
    votes[:, -1] = ~votes[:, :-1].any(axis=1)
    model = LabelModel()
    goal = model.fit(votes)
    w, bias = linear(at, cols, goal, len(chosen))
    return {x: float(w[i]) for x, i in number.items()}, bias, model


def scored(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> DataFrame:
    """All columns of ``docs`` with held_out, score and predicted."""
    weights, bias, _ = fit(docs, labels, most)
    own = [c for c in docs.columns if c.lower() not in ("held_out", "score", "predicted")]
    kept = docs.select(F.struct(*(F.col(f"`{c}`") for c in own)).alias("row"), F.col("text"), held_out().alias("held_out"))
    known: dict[str, tuple[str, ...]] = {}

    def marks(word: str) -> tuple[str, ...]:
        if (found := known.get(word)) is None:
            found = tuple(x for x in features(word) if x in weights)
            if len(known) > 300_000:
                known.clear()
            known[word] = found
        return found

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        z = np.full(batch.num_rows, bias)
        for i, text in enumerate(values(batch.column(1))):
            if text and weights:
                found: set[str] = set()
                for word in set(_word.findall(text.lower())):
                    found.update(marks(word))
                z[i] += sum(weights[x] for x in sorted(found))
        score = np.where(np.isinf(z), 0.0, 1 / (1 + np.exp(-np.clip(z, -500, 500))))
        cols = [batch.column(0).field(c) for c in own]
        return pa.RecordBatch.from_arrays([*cols, batch.column(2), pa.array(score), pa.array((score >= 0.5).astype(np.int32))], [*own, "held_out", "score", "predicted"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*(F.col(f"`{c}`") for c in own)).schema), "held_out boolean", "score double", "predicted int"])
    return arrow_map(kept, each, schema)
