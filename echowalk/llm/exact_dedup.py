"""Exact deduplication by Grace hashing.

Contents (texts without white space) are dealt to partitions by digest; a
partition that does not fit is dealt again into spill files by further digest
bits, until each bucket fits an open-addressing table that compares whole
contents. Each batch is folded by the same table before the exchange, so a
content with any number of copies crosses it once per batch, not once per copy.

Defined results: null text is empty; empty texts equal each other; null ids
come after all others where ids decide; of rows that agree in text and id one
(any) is kept and all name that id; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import pickle
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, numbered, ship, slices, stash, task_id

_BLANKS = bytes([9, 10, 11, 12, 13, 32])
_NO_ID = 2**63 - 1


class ContentTable:
    """Open addressing with linear probing. A slot holds a group; a probe ends at an empty slot or
    at equal content (the stored digest only spares comparisons)."""

    def __init__(self, slots: int = 1 << 10):
        self.slots = [-1] * slots
        self.digest: list[bytes] = []
        self.content: list[bytes] = []
        self.held = 0

    def put(self, digest: bytes, content: bytes) -> int:
        mask = len(self.slots) - 1
        at = int.from_bytes(digest[8:16], "little") & mask
        while (g := self.slots[at]) >= 0:
            if self.digest[g] == digest and self.content[g] == content:
                return g
            at = (at + 1) & mask
        g = self.slots[at] = len(self.content)
        self.digest.append(digest)
        self.content.append(content)
        self.held += len(content) + 120
        if 2 * len(self.content) > len(self.slots):
            self._grow()
        return g

    def _grow(self) -> None:
        mask = 2 * len(self.slots) - 1
        self.slots = [-1] * (mask + 1)
        for g, digest in enumerate(self.digest):
            at = int.from_bytes(digest[8:16], "little") & mask
            while self.slots[at] >= 0:
                at = (at + 1) & mask
            self.slots[at] = g


def grace(records: Iterator[tuple], memory: int, fan_out: int = 16, level: int = 0) -> Iterator[list[list[tuple]]]:
    """Groups of records with equal content. A record starts with digest and content; groups come
    in lists, with content dropped. Spill files are private to the task and have no name, so
    nothing is left of them whatever becomes of the executor."""
    table, rows = ContentTable(), []
    for record in records:
        g = table.put(record[0], record[1])
        if g == len(rows):
            rows.append([])
        rows[g].append((record[0], *record[2:]))
        if table.held > memory and len(rows) > 1 and level < 24:
            break
    else:
        yield rows
        return
    files = [tempfile.TemporaryFile() for _ in range(fan_out)]
    salt = bytes([level])

    def spill(record: tuple) -> None:
        pickle.dump(record, files[hashlib.blake2b(record[0], key=salt, digest_size=1).digest()[0] % fan_out])

    for g, group in enumerate(rows):
        for digest, *rest in group:
            spill((digest, table.content[g], *rest))
    del table, rows
    for record in records:
        spill(record)

    def load(file) -> Iterator[tuple]:
        file.seek(0)
        with file:
            while True:
                try:
                    yield pickle.load(file)
                except EOFError:
                    return

    for file in files:
        yield from grace(load(file), memory, fan_out, level + 1)


_ROWS = pa.schema([("doc_id", pa.int64()), ("uid", pa.int64()), ("gid", pa.int64()), ("digest", pa.binary()), ("content", pa.binary()), ("n", pa.int64()), ("best_chars", pa.int64()), ("best_id", pa.int64()), ("best_uid", pa.int64())])
_ROWS_SQL = "doc_id long, uid long, gid long, digest binary, content binary, n long, best_chars long, best_id long, best_uid long"


def _fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each row with its group in the slice; the group's first row carries content and best row."""
    base = uid = task_id() << 36
    for batch in slices(batches, most=16 << 20):
        ids = batch.column("doc_id").to_pylist()
        texts = batch.column("text")
        chars = pc.utf8_length(texts).to_pylist()
        table, of, best, count = ContentTable(), [], [], []
        for k, text in enumerate(texts.cast(pa.binary())):
            content = text.as_py().translate(None, _BLANKS)
            g = table.put(hashlib.sha256(content).digest(), content)
            of.append(g)
            rank = (-chars[k], _NO_ID if ids[k] is None else ids[k], uid + k)
            if g == len(best):
                best.append(rank)
                count.append(1)
            else:
                best[g] = min(best[g], rank)
                count[g] += 1
        more = [k for k, name in enumerate(batch.schema.names) if name not in ("doc_id", "text")]
        seen: set[int] = set()
        lead = [g not in seen and not seen.add(g) for g in of]
        pick = lambda values: [values[g] if first else None for g, first in zip(of, lead)]
        yield pa.RecordBatch.from_arrays(
            [
                pa.array(ids, pa.int64()),
                pa.array(range(uid, uid + len(of)), pa.int64()),
                pa.array([uid + g for g in of], pa.int64()),
                pa.array([table.digest[g] for g in of], pa.binary()),
                pa.array(pick(table.content), pa.binary()),
                pa.array(pick(count), pa.int64()),
                pa.array(pick([-b[0] for b in best]), pa.int64()),
                pa.array(pick([b[1] for b in best]), pa.int64()),
                pa.array(pick([b[2] for b in best]), pa.int64()),
                *(batch.column(k) for k in more),
            ],
            [*_ROWS.names, *(batch.schema.names[k] for k in more)],
        )
        uid += len(of)
    assert uid - base < 1 << 36


_DONE = pa.schema([("gid", pa.int64()), ("keep_id", pa.int64()), ("keep_uid", pa.int64()), ("group_size", pa.int64())])


def _settle(memory: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def records() -> Iterator[tuple]:
            for batch in batches:
                for part in slices(iter([batch]), "content", 4 << 20):
                    yield from zip(*(part.column(c).to_pylist() for c in ("digest", "content", "gid", "n", "best_chars", "best_id", "best_uid")))

        for groups in grace(records(), memory):
            out: list[tuple] = []
            for group in groups:
                size = sum(r[2] for r in group)
                _, keep, uid = min((-r[3], r[4], r[5]) for r in group)
                out += [(r[1], None if keep == _NO_ID else keep, uid, size) for r in group]
            if out:
                yield pa.record_batch([pa.array(c, pa.int64()) for c in zip(*out)], schema=_DONE)

    return run


def _groups(docs: DataFrame, memory: int, more: str = "") -> DataFrame:
    """Every row of ``docs`` (doc_id, text and the columns of ``more``) with what its group decides."""
    ship(docs.sparkSession)
    rows = stash(docs.mapInArrow(_fold, _ROWS_SQL + more), "contents")
    groups = (
        rows.filter(F.col("content").isNotNull())
        .select("digest", "content", "gid", "n", "best_chars", "best_id", "best_uid")
        .repartition("digest")
        .mapInArrow(_settle(memory), "gid long, keep_id long, keep_uid long, group_size long")
    )
    return rows.drop("content", "n", "best_chars", "best_id", "best_uid").join(groups, "gid").withColumn("kept", F.col("uid") == F.col("keep_uid"))


def exact_duplicates(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", memory: int = 96 << 20) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 for every row of ``df``. Of a group the row
    with the most code points stays, then the smallest id. ``memory``: bytes of distinct content
    that a task holds before it deals them out to spill files."""
    return _groups(documents(df, id_col, text_col), memory).select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


def keep_one(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", memory: int = 96 << 20) -> DataFrame:
    """Rows of ``df``, all columns, one for each content; ids may repeat or be null."""
    df = numbered(df)
    docs = df.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"), "_row")
    kept = _groups(docs, memory, ", _row long").filter("kept").select("_row")
    return df.join(kept, "_row", "left_semi").drop("_row")
