"""Chat formatting: typed content parts, reversible escapes, a loss mask, and the way back.

A message's content is text or a list of typed parts. A visitor flattens the parts in order:
text is escaped, every other part becomes a placeholder and leaves an attachment record with the
tokens that it will expand to. A turn is written as
``<|im_start|>role\\n`` + body + ``<|im_end|>\\n``. Inside bodies and roles ``<`` followed by any
number of backslashes and ``|`` gets one backslash more, so no text can end or open a turn; a
newline in a role is written as a control string of its own. A placeholder is a control string, so
reading a body back gives its typed parts again, and a text that looks like a placeholder stays a text.
"""

from __future__ import annotations

import hashlib
import json
import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ship

# The marks of the template.
START, END = "<|im_start|>", "<|im_end|>"

_ESC, _UNESC = re.compile(r"<(\\*)\|"), re.compile(r"<(\\*)\\\|")
_ROLE_NL = "<|nl|>"


def escape(text: str) -> str:
    """``text`` without any control string; :func:`unescape` gives it back."""
    return _ESC.sub(r"<\1\\|", text)


def unescape(text: str) -> str:
    return _UNESC.sub(r"<\1|", text)


def write_role(role: str) -> str:
    return escape(role).replace("\n", _ROLE_NL)


def read_role(role: str) -> str:
    return unescape(role.replace(_ROLE_NL, "\n"))


def _number(value, least: float = 1.0) -> float:
    """A finite number of at least ``least``; anything else counts as ``least``."""
    try:
        n = float(value)
    except (TypeError, ValueError):
        return least
    return n if math.isfinite(n) and n > least else least


KINDS = ("image", "audio", "document", "unknown")
_PLACE = re.compile(r"<\|(" + "|".join(KINDS) + r"):(\d+)\|>")


class PartVisitor:
    """Flattens typed parts; ``visit`` returns the body, ``attachments`` collects the records.

    Parts: ``{"type": "text", "text"}``, ``{"type": "image", "ref", "width", "height"}``,
    ``{"type": "audio", "ref", "seconds"}``, ``{"type": "document", "ref", "pages"}``. Images
    take a token per ``patch`` x ``patch`` tile, audio ``per_second`` a second, documents
    ``per_page`` a page. No content makes it fail: a bare string is a text part, a single part is a
    list of one, a size that is no positive number counts as the least, and what is no part, or of
    another type, becomes an ``unknown`` placeholder of no tokens whose record keeps it whole.
    """

    def __init__(self, patch: int = 28, per_second: int = 25, per_page: int = 800):
        self.patch, self.per_second, self.per_page = patch, per_second, per_page
        self.attachments: list[dict] = []

    def visit(self, content) -> str:
        if content is None:
            return ""
        if isinstance(content, str):
            return escape(content)
        return "".join(self._part(p) for p in (content if isinstance(content, list) else [content]))

    def _part(self, part) -> str:
        if isinstance(part, str):
            return escape(part)
        kind = part.get("type") if isinstance(part, dict) else None
        visit = {"text": self.visit_text, "image": self.visit_image, "audio": self.visit_audio, "document": self.visit_document}.get(kind if isinstance(kind, str) else None)
        return self.visit_unknown(part) if visit is None else visit(part)

    def visit_text(self, part: dict) -> str:
        text = part.get("text")
        return escape(text if isinstance(text, str) else "" if text is None else json.dumps(text))

    def visit_image(self, part: dict) -> str:
        across, down = (math.ceil(_number(part.get(k)) / self.patch) for k in ("width", "height"))
        return self._place("image", part, across * down)

    def visit_audio(self, part: dict) -> str:
        return self._place("audio", part, max(1, round(_number(part.get("seconds"), 0.0) * self.per_second)))

    def visit_document(self, part: dict) -> str:
        return self._place("document", part, int(_number(part.get("pages"))) * self.per_page)

    def visit_unknown(self, part) -> str:
        return self._place("unknown", part, 0)

    def _place(self, kind: str, part, tokens: int) -> str:
        n = len(self.attachments)
        ref = part.get("ref") if isinstance(part, dict) else None
        self.attachments.append({"index": n, "kind": kind, "ref": ref, "tokens": tokens, "part": part})
        return f"<|{kind}:{n}|>"


def read_body(body: str) -> list[dict]:
    """The typed parts of a body: texts as they were, and placeholders as ``{"type", "index"}``; neighbouring texts are one."""
    out, at = [], 0
    for m in _PLACE.finditer(body):
        if m.start() > at:
            out.append({"type": "text", "text": unescape(body[at : m.start()])})
        out.append({"type": m[1], "index": int(m[2])})
        at = m.end()
    if at < len(body):
        out.append({"type": "text", "text": unescape(body[at:])})
    return out


def read_text(body: str) -> str:
    """All text of a body, without its placeholders."""
    return "".join(p["text"] for p in read_body(body) if p["type"] == "text")


def format_turn(role: str | None, content, train_on: tuple[str, ...] = ("assistant",), visitor: PartVisitor | None = None) -> tuple[str, int, int]:
    """The turn's text and the span of its body that the loss covers (empty for other roles)."""
    body = (visitor or PartVisitor()).visit(content)
    head = f"{START}{write_role(role or '')}\n"
    whole = f"{head}{body}{END}\n"
    return whole, len(head), len(head) + (len(body) if role in train_on else 0)


_TURN = re.compile(re.escape(START) + r"([^\n]*)\n(.*?)" + re.escape(END) + "\n", re.S)


def parse(text: str) -> Iterator[tuple[str, str]]:
    """``(role, text)`` of every turn of a formatted text; raises on anything between turns."""
    for role, body in parse_bodies(text):
        yield role, read_text(body)


def parse_bodies(text: str) -> Iterator[tuple[str, str]]:
    """``(role, body)`` of every turn, the body as written, for :func:`read_body`."""
    at = 0
    for m in _TURN.finditer(text):
        if m.start() != at:
            raise ValueError(f"not a turn at {at}")
        at = m.end()
        yield read_role(m[1]), m[2]
    if at != len(text):
        raise ValueError(f"not a turn at {at}")


L, S = T.LongType(), T.StringType()
FORMATTED = T.StructType([T.StructField("conv_id", L), T.StructField("place", L), T.StructField("formatted", S), T.StructField("loss_from", L), T.StructField("loss_to", L), T.StructField("attachments", S)])
DIGEST = T.StructType([T.StructField("conv_id", L), T.StructField("n_turns", L), T.StructField("turns_sha256", S), T.StructField("loss_chars", L), T.StructField("loss_sha256", S), T.StructField("formatted_chars", L)])


def content_of(parts: str):
    """The content that a JSON value holds; a value that is no JSON, or no list or part, is text as it stands."""
    try:
        got = json.loads(parts)
    except ValueError:
        return parts
    return got if isinstance(got, (list, dict, str)) else parts


def format_conversations(turns: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text", parts_col: str | None = None, train_on: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """One row per turn, in order within its conversation: its formatted text and loss span.

    A conversation's text is its rows' texts back to back (``place`` counts from 0), so the
    longest conversation streams through one task with a turn in memory at a time. ``parts_col``
    names a JSON column of typed parts that, where not null, replaces the text; a value that is no
    JSON is a text. Null text is empty, a null role is the empty role, null turns come first, equal turns are ordered by role
    and text, repeated rows are turns of their own, rows with a null conversation form one
    conversation with a null id; other columns are not read.
    """
    ship(turns.sparkSession)
    cols = [F.col(conv_col).cast("long").alias("conv_id"), F.col(turn_col).alias("turn"), F.col(role_col).cast("string").alias("role"), F.col(text_col).cast("string").alias("text")]
    cols.append((F.col(parts_col).cast("string") if parts_col else F.lit(None).cast("string")).alias("parts"))
    rows = turns.select(*cols).repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").select("conv_id", "role", "text", "parts")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, place, visitor = object(), 0, None
        for b in batches:
            out = []
            for conv, role, text, parts in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                if visitor is None or conv != last:
                    last, place, visitor = conv, 0, PartVisitor()
                seen = len(visitor.attachments)
                whole, lo, hi = format_turn(role, text if parts is None else content_of(parts), train_on, visitor)
                out.append((conv, place, whole, lo, hi, json.dumps(visitor.attachments[seen:])))
                place += 1
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string()]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds, strict=True)], names=FORMATTED.names)

    return rows.mapInArrow(run, FORMATTED)


def digest(formatted: DataFrame) -> DataFrame:
    """Read formatted turns back, row by row in the order written, and sum up each conversation.

    Takes :func:`format_conversations`' output as it is dealt out (whole conversations in a
    partition, in order), or any table after ``in_order``.
    """
    ship(formatted.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state = None
        out: list[tuple] = []
        for b in batches:
            for conv, text, lo, hi in zip(b.column(0).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist(), b.column(4).to_pylist(), strict=True):
                if state is None or state[0] != conv:
                    if state is not None:
                        out.append(_closed(state))
                    state = [conv, 0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                for role, body in parse(text):
                    state[1] += 1
                    state[2].update(f"{role}\n{body}\n".encode())
                loss = read_text(text[lo:hi])
                state[3] += len(loss)
                state[4].update(loss.encode())
                state[5] += len(text)
        if state is not None:
            out.append(_closed(state))
        if out:
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds, strict=True)], names=DIGEST.names)

    return formatted.mapInArrow(run, DIGEST)


def _closed(s: list) -> tuple:
    return s[0], s[1], s[2].hexdigest(), s[3], s[4].hexdigest(), s[5]


def in_order(formatted: DataFrame) -> DataFrame:
    """Whole conversations in a partition, turns in order: for formatted tables read from a store."""
    return formatted.repartition("conv_id").sortWithinPartitions("conv_id", "place")
