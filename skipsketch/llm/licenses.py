"""License scans: exact phrases, and a fuzzy search for short notices.

A notice may differ by up to ``edits`` characters.  Cut into one more segments than that, at least one segment
stands unchanged in any such occurrence (the pigeonhole principle).  An automaton finds all segments in one
pass; around each the bounded-error matching of the regex library decides and gives span and errors.

Defined results: null text is empty: no words, no labels, score 0.  Repeated rows are each returned.  Empty
table: empty result.  Other columns are ignored.
"""

from __future__ import annotations

import bisect
import re
from collections.abc import Iterator
from functools import cache
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skipsketch.llm.common import arrow_map, values

#: Base phrases and their labels.
BASE = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}
#: Short notices in normal form (lower case, single spaces) and their labels.
NOTICES = {
    "released under the mit license": "mit",
    "permission is hereby granted free of charge to any person obtaining a copy": "mit",
    "licensed under the apache license version 2 0": "apache-2",
    "licensed under cc by nc 4 0": "cc-by-nc",
    "licensed under cc by sa 4 0": "cc-by-sa",
    "creative commons attribution 4 0 international": "cc-by",
    "licensed under the gnu general public license": "gpl",
    "gnu lesser general public license": "lgpl",
    "redistribution and use in source and binary forms": "bsd",
    "this source code form is subject to the terms of the mozilla public license": "mpl-2",
    "all rights reserved": "all-rights-reserved",
    "this is free and unencumbered software released into the public domain": "unlicense",
}
#: Characters of a notice for each edit that it may differ by.
PER_EDIT = 10

_NORMAL = bytes(b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else b + 32 if 65 <= b <= 90 else 32 for b in range(256))


def edits(notice: str) -> int:
    return len(notice) // PER_EDIT


def segments(notice: str) -> list[tuple[int, str]]:
    """The notice in edits + 1 pieces of about equal length, with their places."""
    n = edits(notice) + 1
    cuts = [len(notice) * i // n for i in range(n + 1)]
    return [(a, notice[a:b]) for a, b in zip(cuts, cuts[1:])]


@cache
def _search():  # noqa: ANN202
    import ahocorasick
    import regex

    machine = ahocorasick.Automaton()
    at: dict[str, list[tuple[int, int]]] = {}
    for i, notice in enumerate(NOTICES):
        for place, piece in segments(notice):
            at.setdefault(piece, []).append((i, place))
    for piece, where in at.items():
        machine.add_word(piece, (len(piece), where))
    machine.make_automaton()
    patterns = [regex.compile(f"(?b)(?:{regex.escape(x)}){{e<={edits(x)}}}") for x in NOTICES]
    return machine, patterns, list(NOTICES), list(NOTICES.values())


def places(pattern, text: str, a: int, b: int) -> Iterator:  # noqa: ANN001
    """Matches that don't overlap: the best one, and those before and after it."""
    left = [(a, b)]
    while left:
        a, b = left.pop()
        if m := pattern.search(text, a, b):
            yield m
            left += [(a, m.start()), (m.end(), b)]


def notices(text: str) -> list[tuple[int, int, int, int]]:
    """(number of the notice, start, end, errors) in a normal text; overlapping windows of a notice are searched once."""
    machine, patterns, names, _ = _search()
    windows: dict[int, list[list[int]]] = {}
    for end, (size, where) in machine.iter(text):
        for i, place in where:
            slack = edits(names[i])
            a = max(0, end - size + 1 - place - slack)
            b = min(len(text), end - size + 1 - place + len(names[i]) + slack)
            own = windows.setdefault(i, [])
            if own and a <= own[-1][1]:
                own[-1][1] = max(own[-1][1], b)
            else:
                own.append([a, b])
    found = []
    for i, own in windows.items():
        for a, b in own:
            for m in places(patterns[i], text, a, b):
                found.append((i, m.start(), m.end(), sum(m.fuzzy_counts)))
    kept: list[tuple[int, int, int, int]] = []
    taken: list[tuple[int, int]] = []  # what notices of fewer errors cover, as ascending spans apart from each other
    for _, level in groupby(sorted(found, key=lambda x: (x[3], x[1] - x[2], x[1], x[0])), key=lambda x: x[3]):  # of overlapping notices the nearest
        here = [x for x in level if not _meets(taken, x[1], x[2])]
        kept += here
        taken = _spans([*taken, *((x[1], x[2]) for x in here)])
    return sorted(kept, key=lambda x: (x[1], x[2], x[0]))


def _spans(parts: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(parts):
        if out and a < out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], b))
        else:
            out.append((a, b))
    return out


def _meets(spans: list[tuple[int, int]], a: int, b: int) -> bool:
    i = bisect.bisect_left(spans, (b,)) - 1  # the last that begins before b
    return i >= 0 and spans[i][1] > a


_base = re.compile("(?<![^ ])(?=(" + "|".join(BASE) + ")(?![^ ]))")


def scan(text: bytes) -> tuple[int, list[tuple[int, str]], list[tuple[int, int, int, int]], str]:
    """Number of words, (first word, phrase) of base places, notices, and the text in normal form."""
    found = text.translate(_NORMAL).split()
    normal = b" ".join(found).decode("utf-8", "replace")
    base = []
    if any(x in normal for x in BASE):
        at = word = 0
        for m in _base.finditer(normal):  # words are counted on from place to place
            word += normal.count(" ", at, m.start())
            at = m.start()
            base.append((word, m.group(1)))
    return len(found), base, notices(normal), normal


def scanned(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, notices (label, start, end, errors, text)."""

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        names, kinds = list(NOTICES), list(NOTICES.values())
        out: list[list] = [[] for _ in range(8)]
        for text in values(batch.column(1)):
            n, base, fuzzy, normal = scan(text or b"")
            labels = {BASE[x] for _, x in base}
            places = [p for p, _ in base]
            score = max([1.0 if base else 0.0, *(1 - e / len(names[i]) for i, _, _, e in fuzzy)])
            row = (n, len(base), min(places, default=None), max(places, default=None), ",".join(sorted(labels)), ",".join(sorted(labels | {kinds[i] for i, *_ in fuzzy})), score, [{"label": kinds[i], "start": a, "end": b, "errors": e, "text": normal[a:b]} for i, a, b, e in fuzzy])
            for column, x in zip(out, row):
                column.append(x)
        span = pa.struct([("label", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("errors", pa.int64()), ("text", pa.string())])
        kinds_ = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.float64(), pa.list_(span)]
        return pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, t) for c, t in zip(out, kinds_))], ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "notices"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return arrow_map(docs.select("doc_id", F.col("text").cast("binary").alias("text")), each, f"doc_id {kind}, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, notices array<struct<label:string,start:bigint,end:bigint,errors:bigint,text:string>>")
