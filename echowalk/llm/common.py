"""Helpers shared by the training-data operators: tables written to the shared
folder, packed text buffers, vectorised hashes of words and of runs of words.

Null text is the empty text everywhere in this subpackage.
"""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import os
import re
import time
import uuid
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_U = np.uint64
_written: dict[str, SparkSession] = {}


def ship(spark: SparkSession) -> None:
    """Let Python workers of this session import the package from where the driver has it."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    env = spark.sparkContext.environment
    have = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if root not in have:
        env["PYTHONPATH"] = os.pathsep.join([root, *have])


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share; a local one only where the session names none and
    all runs on one machine."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base and not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
    return base or f"/tmp/checkpoints/{spark.sparkContext.applicationId}"


_CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def stash(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, survives lost executors. The
    shuffle files that the write needed go when it is done, where Spark can do that."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
    before = spark.conf.get(_CLEAN, None)
    if before is not None:
        spark.conf.set(_CLEAN, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        if before is not None:
            spark.conf.set(_CLEAN, before)
    out = spark.read.schema(df.schema).parquet(path)
    _written[path] = spark
    out._stash_path = path
    return out


def _delete(path: str) -> None:
    spark = _written.pop(path)
    with contextlib.suppress(Exception):  # the session may have ended
        at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def discard(*tables: DataFrame) -> None:
    """Delete stashed tables that nothing will read again."""
    for t in tables:
        if getattr(t, "_stash_path", None) in _written:
            _delete(t._stash_path)


def stashed() -> set[str]:
    """Paths of all stashed tables that are still there."""
    return set(_written)


def discard_paths(paths: set[str]) -> None:
    for path in paths & set(_written):
        _delete(path)


@atexit.register
def _clear() -> None:
    discard_paths(stashed())


def documents(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text) of ``df``, other columns left behind; null text is empty."""
    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))


#: A row of documents(): its id (least long for null) and a hash of id's nullness and text. Rows that
#: agree in both id and text count as one document.
def row_key(df: DataFrame) -> DataFrame:
    return df.withColumns(
        {
            "_k0": F.coalesce(F.col("doc_id"), F.lit(-(2**63)).cast("long")),
            "_k1": F.xxhash64(F.col("doc_id").isNull(), F.col("text")),
        }
    )


def numbered(df: DataFrame) -> DataFrame:
    """``df`` with a key ``_row`` of every row, since ids may repeat or be null: file and place of rows
    that are read from files, else a number that is written so that it holds."""
    try:
        return df.select("*", F.xxhash64("_metadata.file_path", "_metadata.row_index").alias("_row"))
    except AnalysisException:
        return stash(df.withColumn("_row", F.monotonically_increasing_id()), "numbered")


_tidied = [0.0]


def _tidy() -> None:
    """Give freed memory back: Python workers stay, and share an executor's memory with its JVM."""
    if time.monotonic() - _tidied[0] > 2:
        pa.default_memory_pool().release_unused()
        with contextlib.suppress(AttributeError, OSError):  # where the C library has it
            ctypes.CDLL(None).malloc_trim(0)
        _tidied[0] = time.monotonic()


def slices(batches: Iterator[pa.RecordBatch], text: str = "text", most: int = 1 << 21) -> Iterator[pa.RecordBatch]:
    """Cut batches so that a slice has ``most`` bytes of text or one row."""
    for batch in batches:
        if not batch.num_rows:
            continue
        size = np.cumsum(np.diff(packed(batch.column(text))[1]))
        at = 0
        while at < batch.num_rows:
            done = size[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(size, done + most, "right")))
            yield batch.slice(at, to - at)
            at = to
    _tidy()


def packed(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts in a row, and offsets (one more than texts)."""
    a = pc.fill_null(texts.cast(pa.large_binary()) if pa.types.is_binary(texts.type) else texts.cast(pa.large_string()), b"" if pa.types.is_binary(texts.type) else "")
    off = np.frombuffer(a.buffers()[1], np.int64)[a.offset : a.offset + len(a) + 1] if len(a) else np.zeros(1, np.int64)
    data = np.frombuffer(a.buffers()[2] or b"", np.uint8)[off[0] : off[-1]]
    return data, off - off[0]


def byte_table(lower: bool = True, also_split: bytes = b"") -> np.ndarray:
    """A map of bytes that turns white space (and ``also_split``) to a blank, A-Z to a-z if ``lower``."""
    t = np.arange(256, dtype=np.uint8)
    t[[9, 10, 11, 12, 13, *also_split]] = 32
    if lower:
        t[65:91] = t[65:91] | 32
    return t


class Words:
    """Words of packed texts. ``data``: each word and one blank; word i is data[start[i]:end[i]];
    words of text d are first[d] to first[d + 1]."""

    def __init__(self, texts: pa.Array, table: np.ndarray):
        raw, off = packed(texts)
        b = np.insert(table[raw], off[1:], 32)
        closes = off[1:] + np.arange(1, len(off))
        blank = b == 32
        keep = ~blank
        keep[1:] |= ~blank[:-1]
        ends = np.flatnonzero(blank[1:] & ~blank[:-1]) + 1
        self.first = np.concatenate([[0], np.searchsorted(ends, closes)])
        self.data = b[keep]
        self.end = np.flatnonzero(self.data == 32)
        self.start = np.concatenate([[0], self.end[:-1] + 1]).astype(np.int64) if len(self.end) else np.zeros(0, np.int64)

    def doc_of_word(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))


_NEAR = 64  # bytes of a word whose draws are in tables


@lru_cache(4)
def _draws(key: int) -> np.ndarray:
    return np.random.default_rng(key).integers(0, 2**64, _NEAR * 256, dtype=_U)


def word_hashes(w: Words, key: int = 0) -> np.ndarray:
    """64-bit hashes of words: sums of draws for each byte at its place in the word, without structure
    in either, so that no kind of words collides more than another."""
    if not len(w.start):
        return np.zeros(0, _U)
    size = w.end - w.start
    at = np.arange(len(w.data), dtype=np.int32)
    at -= np.repeat(w.start.astype(np.int32), size + 1)
    far = np.flatnonzero(at >= _NEAR) if size.max() > _NEAR else at[:0]
    at <<= 8
    at |= w.data
    late = at[far].astype(_U)
    at[far] = 0
    drawn = _draws(key)[at]
    if len(far):
        drawn[far] = mix(mix(late + _U(1)) + _U(key + 1))
    drawn[w.end] = 0  # blanks
    return np.add.reduceat(drawn, w.start)


_PRIME = 2**61 - 1
_P = _U(_PRIME)


def _reduced(x: np.ndarray) -> np.ndarray:
    x = (x & _P) + (x >> _U(61))
    return np.where(x >= _P, x - _P, x)


def _times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Products modulo 2**61 - 1."""
    a1, a0, b1, b0 = a >> _U(31), a & _U(2**31 - 1), b >> _U(31), b & _U(2**31 - 1)
    middle = a0 * b1 + a1 * b0
    return _reduced((a1 * b1 << _U(1)) + (middle >> _U(30)) + ((middle & _U(2**30 - 1)) << _U(31)) + a0 * b0)


class SpanHash:
    """Hashes of runs of words (given by 64-bit hashes) from prefix sums: sum of word * base**place
    modulo the prime 2**61 - 1, times base**-first, then mixed. Two different runs of n words are
    zeros' apart in a polynomial of degree n, so at most n of the 2**61 bases confuse them; ``key``
    chooses the base."""

    _tables: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def __init__(self, words: np.ndarray, key: int = 0):
        power, self.inverse = self._powers(len(words) + 1, key)
        terms = _times(_reduced(words), power[: len(words)])
        low, high = np.cumsum(terms & _U(2**32 - 1), dtype=_U), np.cumsum(terms >> _U(32), dtype=_U)
        self.sums = np.zeros(len(words) + 1, _U)
        self.sums[1:] = _reduced((high >> _U(29)) + ((high & _U(2**29 - 1)) << _U(32)) + low)

    @classmethod
    def _powers(cls, n: int, key: int) -> tuple[np.ndarray, np.ndarray]:
        have = cls._tables.get(key)
        if have is None or len(have[0]) < n:
            base, have = int(np.random.default_rng([key, 61]).integers(2**32, _PRIME - 1)), []
            for x in (base, pow(base, -1, _PRIME)):
                powers = np.ones(1, _U)
                while len(powers) < max(n, 1 << 20):
                    powers = np.concatenate([powers, _times(powers, np.full(1, pow(x, len(powers), _PRIME), _U))])
                have.append(powers)
            cls._tables[key] = have = tuple(have)
        return have

    def of(self, first: np.ndarray, last: np.ndarray) -> np.ndarray:
        """Hashes of the words from ``first`` to ``last``, both included."""
        return mix(_times(_reduced(self.sums[last + 1] + (_P - self.sums[first])), self.inverse[first]))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit words."""
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def distinct(x: np.ndarray) -> np.ndarray:
    """Sorted distinct values, by a sort (np.unique without more to return hashes, at many times the time)."""
    x = np.sort(x)
    return x[np.concatenate([[True], x[1:] != x[:-1]])] if len(x) else x


def task_id() -> int:
    from pyspark import TaskContext

    context = TaskContext.get()
    return context.partitionId() if context else 0
