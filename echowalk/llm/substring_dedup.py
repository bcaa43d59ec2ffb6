"""Substring deduplication by seed and extend.

Seeds: every window of ``window`` words has one anchor, the least hash of its
word k-grams (winnowing), so equal windows share their anchor. An anchor's
extent is the run of windows that it is the anchor of. Documents are joined on
their anchors: occurrences whose whole extents are equal repeat all their
windows and need no more; where an anchor has several extents, one occurrence of
each is extended to the left and right window by window, and the windows are
joined. Runs of repeated windows are the maximal repeats.

What is equal within a batch is settled there and sent on once, so a passage
that any number of documents share meets itself once a batch. Extents and windows
count as equal where two hashes of their words with independent draws agree, 122
bits in all: of n words, at most n in 2**61 bases of each confuse two runs, whatever
the words are (an extent has less than two windows of words).

Defined results: each row is a document, also where rows repeat; null text has
no words; texts shorter than a window lose nothing; an empty table gives no
rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import SpanHash, Words, byte_table, discard, documents, row_key, ship, slices, stash, word_hashes

_AS_IS = byte_table(lower=False)
_PLACE = np.uint64(30)  # bits of a position beside the hash in the winnowing order
_FULL, _SHOW, _ASK = 0, 1, 2  # a decided extent; one whose windows others may match; one whose windows ask
_NEED, _SENT, _DECIDED = 0, 1, 2


def _sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """The least of each ``width`` neighbours: of suffix and prefix minima within blocks."""
    n = len(x)
    full = np.full(-(-n // width) * width, np.iinfo(x.dtype).max, x.dtype)
    full[:n] = x
    blocks = full.reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[: n - width + 1], ahead[width - 1 : n])


def anchors(w: Words, hashes: SpanHash, window: int, gram: int) -> tuple[np.ndarray, ...]:
    """Anchor's word, first and last window start, and text of each extent."""
    n, width = len(w.start), window - gram + 1
    none = (np.zeros(0, np.int64),) * 4
    if n < window:
        return none
    first = np.arange(n - gram + 1)
    h = hashes.of(first, first + gram - 1)
    low = _sliding_min((h >> _PLACE << _PLACE) | np.arange(len(h), dtype=np.uint64), width)
    at = (low & np.uint64((1 << 30) - 1)).astype(np.int64)
    doc = w.doc_of_word()
    start = np.flatnonzero(doc[: n - window + 1] == doc[window - 1 :])
    if not len(start):
        return none
    at, own = at[start], doc[start]
    new = np.flatnonzero(np.concatenate([[True], (at[1:] != at[:-1]) | (own[1:] != own[:-1])]))
    last = np.concatenate([new[1:], [len(start)]]) - 1
    return at[new], start[new], start[last], own[new]


def _both(w: Words) -> tuple[SpanHash, SpanHash]:
    return tuple(SpanHash(word_hashes(w, key), key) for key in (0, 1))


def _settle_locally(h1: np.ndarray, h2: np.ndarray, asks: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """States after what is equal here is settled: of equals one is sent; the others' keys give way
    to keys of their own, so that no key is crowded."""
    order = np.lexsort((h2, h1))
    a, b = h1[order], h2[order]
    new = np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])])
    run = np.cumsum(new) - 1
    alone = np.bincount(run)[run] == 1
    state = np.empty(len(h1), np.int8)
    state[order] = np.where(new, np.where(alone & asks[order], _NEED, _SENT), _DECIDED)
    h1, h2 = h1.copy(), h2.copy()
    gone = state == _DECIDED
    h1[gone] ^= np.random.default_rng(len(h1)).integers(1, 2**63, gone.sum(), dtype=np.uint64)
    h2[gone] = np.arange(gone.sum(), dtype=np.uint64)
    return h1, h2, state


_EXTENTS = "h1 long, h2 long, a long, k0 long, k1 long, lo int, hi int, state int"


def _extents(window: int, gram: int, hold: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def done() -> pa.RecordBatch:
            h1, h2, a, k0, k1, lo, hi = (np.concatenate(c) for c in zip(*held))
            h1, h2, state = _settle_locally(h1, h2, np.ones(len(h1), bool))
            cols = [h1.view(np.int64), h2.view(np.int64), a.view(np.int64), k0, k1, lo.astype(np.int32), hi.astype(np.int32), state.astype(np.int32)]
            return pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["h1", "h2", "a", "k0", "k1", "lo", "hi", "state"])

        for batch in slices(batches):
            w = Words(batch.column("text"), _AS_IS)
            one, two = _both(w)
            at, lo, hi, doc = anchors(w, one, window, gram)
            end = hi + window - 1
            first = w.first[doc]
            k0, k1 = (np.asarray(batch.column(c))[doc] for c in ("_k0", "_k1"))
            held.append((one.of(lo, end), two.of(lo, end), one.of(at, at + gram - 1), k0, k1, lo - first, hi - first))
            if sum(len(x[0]) for x in held) >= hold:
                yield done()
                held = []
        if held:
            yield done()

    return run


def _covered(n: int, ranges: list[tuple[int, int]], window: int) -> np.ndarray:
    """Words covered by windows that start in any of the ranges (ends included)."""
    step = np.zeros(n + 1, np.int32)
    for lo, hi in ranges:
        step[lo] += 1
        step[hi + window] -= 1
    return np.cumsum(step[:-1]) > 0


_OUT = pa.schema(
    [("doc_id", pa.int64()), ("k0", pa.int64()), ("k1", pa.int64()), ("kind", pa.int32()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string()), ("kept_text", pa.string())]
    + [("text", pa.string()), ("ranges", pa.list_(pa.int32())), ("h1", pa.int64()), ("h2", pa.int64()), ("at", pa.int32()), ("state", pa.int32())]
)
_OUT_SQL = "doc_id long, k0 long, k1 long, kind int, n_words long, n_removed long, kept_sha256 string, kept_text string, text string, ranges array<int>, h1 long, h2 long, at int, state int"
_DONE, _PENDING, _WINDOW = 0, 1, 2


def _rows(kind: int, n: int, **columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) if f.name in columns else pa.array([kind] * n, f.type) if f.name == "kind" else pa.nulls(n, f.type) for f in _OUT], schema=_OUT)


def _kept(w: Words, d: int, ranges: list[tuple[int, int]], window: int, with_text: bool) -> tuple[int, int, str, str | None]:
    """Words, words removed, digest and (if wanted) text of what is kept of text ``d``."""
    a, b = int(w.first[d]), int(w.first[d + 1])
    if a == b:
        return 0, 0, hashlib.sha256(b"").hexdigest(), "" if with_text else None
    own = w.data[w.start[a] : w.end[b - 1] + 1]
    removed = 0
    if ranges:
        gone = _covered(b - a, ranges, window)
        removed = int(gone.sum())
        own = own[np.repeat(~gone, w.end[a:b] - w.start[a:b] + 1)]
    text = own[:-1].tobytes()
    return b - a, removed, hashlib.sha256(text).hexdigest(), text.decode() if with_text else None


def _extend(window: int, hold: int, with_text: bool):
    """Documents with the decisions on their extents: finished, or pending with windows to join."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def windows() -> pa.RecordBatch:
            h1, h2, k0, k1, at, asks = (np.concatenate(c) for c in zip(*held))
            h1, h2, state = _settle_locally(h1, h2, asks)
            # what only shows needs no answer
            useful = asks | (state != _DECIDED)
            return _rows(_WINDOW, int(useful.sum()), h1=h1.view(np.int64)[useful], h2=h2.view(np.int64)[useful], k0=k0[useful], k1=k1[useful], at=at[useful], state=np.where(asks, np.where(state == _NEED, _NEED, np.where(state == _SENT, _SENT, _DECIDED)), _SENT + 2)[useful])

        for batch in slices(batches):
            w = Words(batch.column("text"), _AS_IS)
            ids, texts = batch.column("doc_id").to_pylist(), batch.column("text")
            keys = [np.asarray(batch.column(c)) for c in ("_k0", "_k1")]
            done, pending, starts, owners, asking = [], [], [], [], []
            for d, said in enumerate(batch.column("said")):
                said = said.values
                lo, hi, kind = (np.asarray(said.field(c)) for c in ("lo", "hi", "kind")) if said is not None and len(said) else (np.zeros(0, np.int64),) * 3
                full = list(zip(lo[kind == _FULL].tolist(), hi[kind == _FULL].tolist()))
                for a, b, k in zip(lo[kind != _FULL].tolist(), hi[kind != _FULL].tolist(), kind[kind != _FULL].tolist()):
                    starts.append(np.arange(a, b + 1) + w.first[d])
                    owners.append(np.full(b - a + 1, d))
                    asking.append(np.full(b - a + 1, k == _ASK))
                if (kind == _ASK).any():
                    pending.append((ids[d], keys[0][d], keys[1][d], texts[d].as_py(), [x for r in full for x in r]))
                else:
                    done.append((ids[d], *_kept(w, d, full, window, with_text)))
            if done:
                yield _rows(_DONE, len(done), **dict(zip(("doc_id", "n_words", "n_removed", "kept_sha256", "kept_text"), zip(*done))))
            if pending:
                yield _rows(_PENDING, len(pending), **dict(zip(("doc_id", "k0", "k1", "text", "ranges"), zip(*pending))))
            if starts:
                start, owner, asks = np.concatenate(starts), np.concatenate(owners), np.concatenate(asking)
                one, two = _both(w)
                held.append((one.of(start, start + window - 1), two.of(start, start + window - 1), keys[0][owner], keys[1][owner], (start - w.first[owner]).astype(np.int32), asks))
                if sum(len(x[0]) for x in held) >= hold:
                    yield windows()
                    held = []
        if held:
            yield windows()

    return run


def _finish(window: int, with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            w = Words(batch.column("text"), _AS_IS)
            rows = []
            for d, (doc, ranges, at) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("doc_id", "ranges", "at")))):
                ranges = list(zip(ranges[::2], ranges[1::2])) + [(x, x) for x in at or ()]
                rows.append((doc, *_kept(w, d, ranges, window, with_text)))
            yield _rows(_DONE, len(rows), **dict(zip(("doc_id", "n_words", "n_removed", "kept_sha256", "kept_text"), zip(*rows))))

    return run


def remove_repeats(df: DataFrame, window: int = 35, gram: int = 6, id_col: str = "doc_id", text_col: str = "text", hold: int = 400_000, with_text: bool = True) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256, kept_text for every row of ``df``: words covered by
    a window that also starts elsewhere are removed, the others joined by blanks. ``hold``: extents
    or windows that a task settles at once."""
    ship(df.sparkSession)
    docs = row_key(documents(df, id_col, text_col))
    sent = docs.mapInArrow(_extents(window, gram, hold), _EXTENTS)
    equal = Window.partitionBy("h1", "h2")
    settled = sent.withColumns({"n": F.count(F.lit(1)).over(equal), "nth": F.row_number().over(equal.orderBy("k0", "k1", "lo"))})
    settled = stash(settled.select("a", "k0", "k1", "lo", "hi", ((F.col("state") != _NEED) | (F.col("n") > 1)).alias("full"), ((F.col("nth") == 1) & (F.col("state") != _DECIDED)).alias("lead")), "extents")
    lead = settled.filter("lead")
    several = lead.groupBy("a").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("a")
    mixed = stash(lead.join(several, "a", "left_semi").select("k0", "k1", "lo", "hi", F.when(F.col("full"), _SHOW).otherwise(_ASK).alias("kind")), "mixed-extents")
    said = settled.filter("full").select("k0", "k1", "lo", "hi", F.lit(_FULL).alias("kind")).union(mixed)
    said = said.groupBy(F.col("k0").alias("_k0"), F.col("k1").alias("_k1")).agg(F.collect_list(F.struct("lo", "hi", "kind")).alias("said"))
    joined = docs.join(said, ["_k0", "_k1"], "left").select("doc_id", "_k0", "_k1", "text", "said")
    step = stash(joined.mapInArrow(_extend(window, hold, with_text), _OUT_SQL), "extended")
    discard(settled, mixed)
    ask = step.filter(F.col("kind") == _WINDOW).select("h1", "h2", "k0", "k1", "at", "state")
    found = ask.withColumn("n", F.count(F.lit(1)).over(equal)).filter(((F.col("state") == _NEED) & (F.col("n") > 1)) | F.col("state").isin(_SENT, _DECIDED))
    found = found.groupBy("k0", "k1").agg(F.collect_list("at").alias("at"))
    columns = ["doc_id", "n_words", "n_removed", "kept_sha256", *(["kept_text"] if with_text else [])]
    late = step.filter(F.col("kind") == _PENDING).select("doc_id", "k0", "k1", "text", "ranges").join(found, ["k0", "k1"], "left").select("doc_id", "text", "ranges", "at")
    late = late.mapInArrow(_finish(window, with_text), _OUT_SQL)
    return step.filter(F.col("kind") == _DONE).select(*columns).union(late.select(*columns))
