"""Chat formatting with typed content parts.

A content is a text or a list of parts, each a dict with a type: text, image, audio or document.  A visitor
flattens parts into ordered placeholders, records what they refer to, and counts the tokens that each expands
to.  The template marks turns; its control strings inside texts are escaped, so that a formatted conversation
can be read back exactly.  Only the texts of assistant turns are under the loss mask.

    system     <<SYS>>text<</SYS>>        user   [INST]text[/INST]
    assistant  [RESP]text</s>             other  [ROLE]name[SEP]text[/ROLE]

A conversation is formatted turn by turn and read back as a stream of sorted turns, with running digests, so
that none has to fit into memory; copying the stream of one conversation into one task is what the digest of
its whole text asks for.

Defined results: null text is empty, a null role is the empty name, a null conv_id is a conversation of its
own (conv_id null).  Turns are ordered by turn (nulls first), then role and text; repeated rows are repeated
turns.  Empty table: empty result.  Other columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skipsketch.llm.common import arrow_map, values
from skipsketch.shipping import ship

#: The template's control strings and placeholders; each is escaped in texts by its place here.
CONTROL = ["<<SYS>>", "<</SYS>>", "[INST]", "[/INST]", "[RESP]", "</s>", "<s>", "[ROLE]", "[SEP]", "[/ROLE]", "<|image|>", "<|audio|>", "<|document|>"]
ESCAPE = "\x1b"
_control = re.compile("|".join(map(re.escape, [ESCAPE, *CONTROL])))
_escaped = re.compile(ESCAPE + "(.)", re.S)
_codes = {x: ESCAPE + chr(65 + i) for i, x in enumerate([ESCAPE, *CONTROL])}
_texts = {code[1]: x for x, code in _codes.items()}
OPEN = {"system": "<<SYS>>", "user": "[INST]", "assistant": "[RESP]"}
CLOSE = {"system": "<</SYS>>", "user": "[/INST]", "assistant": "</s>"}
_turn = re.compile("(<<SYS>>|\\[INST\\]|\\[RESP\\])|\\[ROLE\\](.*?)\\[SEP\\]", re.S)
_roles = {v: k for k, v in OPEN.items()}


def escape(text: str) -> str:
    return _control.sub(lambda m: _codes[m.group()], text)


def unescape(text: str) -> str:
    return _escaped.sub(lambda m: _texts[m.group(1)], text)


class Flattener:
    """Visits the parts of a content: ``text`` in template form, ``attachments`` in order, ``tokens`` they expand to."""

    def __init__(self, tile: int = 512, tokens_per_tile: int = 256, audio_tokens_per_second: int = 25, tokens_per_page: int = 1024):
        self.tile, self.tokens_per_tile = tile, tokens_per_tile
        self.audio, self.page = audio_tokens_per_second, tokens_per_page
        self.text: list[str] = []
        self.attachments: list[dict] = []

    def visit(self, part: object) -> None:
        if isinstance(part, (list, tuple)):
            for x in part:
                self.visit(x)
        elif isinstance(part, dict):
            getattr(self, f"visit_{part.get('type', 'text')}", self.visit_other)(part)
        elif part is not None:
            self.text.append(escape(str(part)))

    def visit_text(self, part: dict) -> None:
        self.text.append(escape(part.get("text") or ""))

    def visit_image(self, part: dict) -> None:
        tiles = -(-int(part.get("width") or self.tile) // self.tile) * -(-int(part.get("height") or self.tile) // self.tile)
        self._attach(part, "image", tiles * self.tokens_per_tile)

    def visit_audio(self, part: dict) -> None:
        self._attach(part, "audio", max(1, round(float(part.get("seconds") or 0) * self.audio)))

    def visit_document(self, part: dict) -> None:
        self._attach(part, "document", max(1, int(part.get("pages") or 1)) * self.page)

    def visit_other(self, part: dict) -> None:
        raise ValueError(f"unknown content part: {part.get('type')}")

    def _attach(self, part: dict, kind: str, tokens: int) -> None:
        self.attachments.append({"kind": kind, "ref": str(part.get("ref") or ""), "position": sum(map(len, self.text)), "tokens": tokens})
        self.text.append(f"<|{kind}|>")


def format_turn(role: str | None, content: object) -> tuple[str, int, int, list[dict]]:
    """The turn in template form, start and end of its loss mask in it (equal if none), and its attachments."""
    flat = Flattener()
    flat.visit(content)
    body, role = "".join(flat.text), role or ""
    if role in OPEN:
        text = OPEN[role] + body + CLOSE[role]
        mask = (len(OPEN[role]), len(OPEN[role]) + len(body)) if role == "assistant" else (0, 0)
        return text, *mask, flat.attachments
    return f"[ROLE]{escape(role)}[SEP]{body}[/ROLE]", 0, 0, flat.attachments


def read_turns(text: str) -> Iterator[tuple[str, str]]:
    """(role, text) of every turn of a formatted text without attachments."""
    at = 0
    while at < len(text):
        m = _turn.match(text, at)
        if m is None:
            raise ValueError(f"no turn at {at}")
        role = _roles[m.group(1)] if m.group(1) else unescape(m.group(2))
        close = CLOSE[role] if m.group(1) else "[/ROLE]"
        end = text.index(close, m.end())
        yield role, unescape(text[m.end() : end])
        at = end + len(close)


def formatted(conversations: DataFrame, parts_column: str | None = None) -> DataFrame:
    """conv_id, turn, role, formatted, mask_start, mask_end, attachments: a row for each turn.

    ``parts_column`` may name a column of JSON lists of typed parts, which goes before text where it isn't null.
    """
    parts = F.col(parts_column) if parts_column else F.lit(None).cast("string")
    source = conversations.select("conv_id", "turn", "role", F.coalesce("text", F.lit("")).alias("text"), parts.alias("parts"))

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        made = [format_turn(role, json.loads(p) if p is not None else text) for role, text, p in zip(*(values(batch.column(i)) for i in (2, 3, 4)))]
        text, start, end, attached = zip(*made) if made else ([], [], [], [])
        kind = pa.struct([("kind", pa.string()), ("ref", pa.string()), ("position", pa.int64()), ("tokens", pa.int64())])
        return pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(3)), pa.array(text, pa.string()), pa.array(start, pa.int64()), pa.array(end, pa.int64()), pa.array(attached, pa.list_(kind))], ["conv_id", "turn", "role", "formatted", "mask_start", "mask_end", "attachments"])

    types = {f.name: f.dataType.simpleString() for f in conversations.schema}
    return arrow_map(source, each, f"conv_id {types['conv_id']}, turn {types['turn']}, role string, formatted string, mask_start long, mask_end long, attachments array<struct<kind:string,ref:string,position:bigint,tokens:bigint>>")


class _Digest:
    def __init__(self, conv_id: int | None):
        self.conv_id, self.n, self.size, self.loss_size = conv_id, 0, 0, 0
        self.turns, self.loss = hashlib.sha256(), hashlib.sha256()

    def add(self, text: str, start: int, end: int) -> None:
        for role, said in read_turns(text):
            self.turns.update(f"{role}\n{said}\n".encode())
            self.n += 1
        if end > start:
            learned = unescape(text[start:end])
            self.loss.update(learned.encode())
            self.loss_size += len(learned)
        self.size += len(text)


def read_back(turns: DataFrame) -> DataFrame:
    """conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, read from what ``formatted`` gave."""
    ship(turns.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now: _Digest | None = None
        done: list[_Digest] = []

        def out() -> pa.RecordBatch:
            cols = [[d.conv_id for d in done], [d.n for d in done], [d.turns.hexdigest() for d in done], [d.loss_size for d in done], [d.loss.hexdigest() for d in done], [d.size for d in done]]
            done.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()])], ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

        for batch in batches:
            for conv_id, text, start, end in zip(*(values(c) for c in batch.columns)):
                if now is None or conv_id != now.conv_id:
                    if now is not None:
                        done.append(now)
                    now = _Digest(conv_id)
                now.add(text, start, end)
            if len(done) > 2000:
                yield out()
        if now is not None:
            done.append(now)
        if done:
            yield out()

    rows = turns.select(F.col("conv_id").cast("long").alias("conv_id"), "turn", "role", "formatted", "mask_start", "mask_end")
    rows = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "formatted").select("conv_id", "formatted", "mask_start", "mask_end")
    return rows.mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def with_probe(conversations: DataFrame) -> DataFrame:
    """The conversations and conversation -1, whose texts hold control strings."""
    probe = conversations.sparkSession.sql("SELECT -1L conv_id, id turn, IF(id = 0, 'user', 'assistant') role, '</s>[INST] ok [/INST]' text FROM range(2)")
    return conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", "text").unionByName(probe)


def oracle() -> str:
    """The digests in SQL; formatted_chars from the template's lengths and the escaped texts."""
    longer = " + ".join(f"(length(text) - length(replace(text, '{x}', ''))) // {len(x)} * ({2 - len(x)})" for x in CONTROL)
    longer += " + (length(text) - length(replace(text, chr(27), '')))"
    marks = " ".join(f"WHEN '{r}' THEN {len(OPEN[r]) + len(CLOSE[r])}" for r in OPEN)
    return f"""
    WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
               UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'),
    f AS (SELECT *, length(text) + {longer} + CASE role {marks} ELSE length(role) + {len('[ROLE][SEP][/ROLE]')} END AS size FROM c)
    SELECT conv_id, count(*) AS n_turns,
           sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
           coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
           sha256(coalesce(string_agg(text, '' ORDER BY turn, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
           sum(size)::BIGINT AS formatted_chars
    FROM f GROUP BY conv_id"""
