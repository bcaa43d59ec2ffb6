"""Chat formatting by incremental rendering of a black-box template.

A template is any function from a list of (role, text) to a string. The
operator renders successive prefixes of a conversation and compares each output
with the one before: what follows the old output is the new turn's span; where
the old output is no prefix of the new one, the template rewrites history and
the turn says so. A template that declares ``lookback`` (its rendering of a
turn depends on that many turns before it, at most) is rendered over prefixes
of a sliding window, so a conversation of any length takes linear time and
constant memory; others are rendered over whole prefixes.

Defined results: turns are ordered by turn (null first), then role and text;
null role or text is empty; a null conv_id is one conversation of its own;
repeated rows are repeated turns; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship

Turn = tuple[str, str]

#: What each sign that can start or end a mark becomes inside a text.
ESCAPES = (("~", "~0"), ("<", "~1"), ("[", "~2"), ("]", "~3"))


def escape(text: str) -> str:
    for sign, code in ESCAPES:
        text = text.replace(sign, code)
    return text


def unescape(text: str) -> str:
    for sign, code in reversed(ESCAPES):
        text = text.replace(code, sign)
    return text


@dataclass(frozen=True)
class Template:
    name: str
    render: Callable[[Sequence[Turn]], str]
    lookback: int | None = None


def _marked(turns: Sequence[Turn]) -> str:
    out = []
    for role, text in turns:
        if role == "assistant":
            out.append(f"<s>{escape(text)}</s>")
        else:
            out.append(f"[INST {escape(role)}]{escape(text)}[/INST]")
    return "".join(out)


def _headers(turns: Sequence[Turn]) -> str:
    return "".join(f"<|start|>{escape(role)}\n{escape(text)}<|end|>\n" for role, text in turns)


def _last_reasoning_only(turns: Sequence[Turn]) -> str:
    """Drops what earlier assistant turns have between <think> tags: rewrites history."""
    last = max((k for k, t in enumerate(turns) if t[0] == "assistant"), default=-1)
    return _headers([(r, re.sub("(?s)<think>.*?</think>", "", t) if r == "assistant" and k != last else t) for k, (r, t) in enumerate(turns)])


MARKED = Template("marked", _marked, 0)
HEADERS = Template("headers", _headers, 0)
LAST_REASONING = Template("last_reasoning", _last_reasoning_only)

_TURN = re.compile(r"(?s)<s>([^<\[]*)</s>|\[INST ([^<\[\]]*)\]([^<\[]*)\[/INST\]")


def read_back(text: str) -> list[tuple[Turn, int, int]]:
    """Turns of a ``MARKED`` rendering and the span of each one's (escaped) text."""
    out, at = [], 0
    while at < len(text):
        m = _TURN.match(text, at)
        if not m:
            raise ValueError(f"not a rendered turn at {at}: {text[at : at + 40]!r}")
        group = 1 if m[1] is not None else 3
        out.append((("assistant" if group == 1 else unescape(m[2]), unescape(m[group])), *m.span(group)))
        at = m.end()
    return out


@dataclass
class Piece:
    """What turn ``k`` adds: the text from ``start`` on; if ``rewrites``, that replaces all output behind ``start``."""

    k: int
    start: int
    text: str
    rewrites: bool


def increments(turns: Iterator[Turn], template: Template) -> Iterator[Piece]:
    """A piece for every turn, from renderings of successive prefixes."""
    window: list[Turn] = []
    before, gone = "", 0
    for k, turn in enumerate(turns):
        if template.lookback is not None and len(window) > 2 * template.lookback + 16:
            window = window[len(window) - template.lookback :] if template.lookback else []
            kept = template.render(window)
            gone += len(before) - len(kept)
            before = kept
        window.append(turn)
        after = template.render(window)
        if after.startswith(before):
            yield Piece(k, gone + len(before), after[len(before) :], False)
        else:
            same = _common_prefix(before, after)
            yield Piece(k, gone + same, after[same:], True)
        before = after


def _common_prefix(a: str, b: str) -> int:
    low, high = 0, min(len(a), len(b))
    while low < high:
        mid = (low + high + 1) // 2
        low, high = (mid, high) if a[:mid] == b[:mid] else (low, mid - 1)
    return low


def _turns_in_order(df: DataFrame) -> DataFrame:
    text = lambda c: F.coalesce(F.col(c), F.lit("")).alias(c)
    rows = df.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), text("role"), text("text"))
    return rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")


def _conversations(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int | None, Iterator[Turn]]]:
    from itertools import groupby

    rows = (row for b in batches for row in zip(*(b.column(c).to_pylist() for c in ("conv_id", "role", "text"))))
    for conv, group in groupby(rows, key=lambda r: r[0]):
        yield conv, ((role, text) for _, role, text in group)


_SPANS = pa.schema([("conv_id", pa.int64()), ("turn_no", pa.int64()), ("role", pa.string()), ("start", pa.int64()), ("piece", pa.string()), ("rewrites", pa.bool_())])


def format_turns(df: DataFrame, template: Template = MARKED) -> DataFrame:
    """conv_id, turn_no (from 0), role, start (offset in the conversation's rendering), piece,
    rewrites: one row for every turn; pieces in order, without rewrites, are the rendering."""
    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        for conv, turns in _conversations(batches):
            roles: list[str] = []
            for p in increments((roles.append(t[0]) or t for t in turns), template):
                rows.append((conv, p.k, roles.pop(), p.start, p.text, p.rewrites))
                if len(rows) >= 2000:
                    yield pa.record_batch([pa.array(c, f.type) for c, f in zip(zip(*rows), _SPANS)], schema=_SPANS)
                    rows = []
        if rows:
            yield pa.record_batch([pa.array(c, f.type) for c, f in zip(zip(*rows), _SPANS)], schema=_SPANS)

    return _turns_in_order(df).mapInArrow(run, "conv_id long, turn_no long, role string, start long, piece string, rewrites boolean")


_DIGEST = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64()), ("rewrites", pa.int64())])


def format_digests(df: DataFrame) -> DataFrame:
    """One row for every conversation, all read back from the ``MARKED`` rendering piece by piece:
    digests of its turns and of the texts under the loss mask (assistant turns)."""
    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = []
        for conv, turns in _conversations(batches):
            seen, loss = hashlib.sha256(), hashlib.sha256()
            n = chars = size = rewrites = 0
            for piece in increments(turns, MARKED):
                rewrites += piece.rewrites
                size = piece.start + len(piece.text)
                for (role, text), _, _ in read_back(piece.text):
                    n += 1
                    seen.update(f"{role}\n{text}\n".encode())
                    if role == "assistant":
                        chars += len(text)
                        loss.update(text.encode())
            rows.append((conv, n, seen.hexdigest(), chars, loss.hexdigest(), size, rewrites))
            if len(rows) >= 5000:
                yield pa.record_batch([pa.array(c, f.type) for c, f in zip(zip(*rows), _DIGEST)], schema=_DIGEST)
                rows = []
        if rows:
            yield pa.record_batch([pa.array(c, f.type) for c, f in zip(zip(*rows), _DIGEST)], schema=_DIGEST)

    return _turns_in_order(df).mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, rewrites long")
