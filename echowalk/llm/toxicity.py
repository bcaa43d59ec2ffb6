"""Toxicity scores by FTRL-proximal logistic regression.

Features are hashes of word 1-grams, 2-grams and skip-grams (two words with one
or two between them left out), each counted once a text. Learning rates are
per coordinate, L1 leaves few weights, and only those are sent to the executors
(at most 2**bits of them, whatever the input). Labels are learned from a sample
of labelled texts bounded by ``sample``, thinned by a hash of the id.

Defined results: null and empty texts get the score of the bias alone; without
labelled rows all scores are 0; rows are scored one by one, so repeated rows
get equal scores; labels that are null are not learned from.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Words, byte_table, distinct, documents, mix, ship, slices, word_hashes

#: Words end at white space and at ASCII signs that are no letters or digits.
_TABLE = byte_table(lower=True, also_split=bytes(b for b in range(1, 128) if not chr(b).isalnum()))
_SKIPS = (1, 2, 3)


def features(texts: pa.Array, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Indices below 2**bits of the features of all texts, and the number of each text's."""
    w = Words(texts, _TABLE)
    h = word_hashes(w)
    doc = w.doc_of_word()
    shift = np.uint64(64 - bits)
    index, owner = [h >> shift], [doc]
    for skip in _SKIPS:
        if len(h) > skip:
            same = doc[skip:] == doc[:-skip]
            pair = mix(h[:-skip][same] * np.uint64(3) + (h[skip:][same] << np.uint64(1)) + np.uint64(skip))
            index.append(pair >> shift)
            owner.append(doc[:-skip][same])
    key = distinct((np.concatenate(owner).astype(np.uint64) << np.uint64(bits)) | np.concatenate(index))
    return (key & np.uint64((1 << bits) - 1)).astype(np.int64), np.bincount((key >> np.uint64(bits)).astype(np.int64), minlength=len(texts))


@dataclass(frozen=True)
class Weights:
    """Sparse weights: sorted indices and their values; ``bias``; feature space of 2**bits."""

    index: np.ndarray
    value: np.ndarray
    bias: float
    bits: int

    def scorer(self):
        dense = np.zeros(1 << self.bits, np.float32)
        dense[self.index] = self.value

        def score(texts: pa.Array) -> np.ndarray:
            index, count = features(texts, self.bits)
            total = np.concatenate([[0.0], np.cumsum(dense[index], dtype=np.float64)])
            end = np.cumsum(count)
            margin = np.clip(total[end] - total[end - count] + self.bias, -30, 30)
            return 1 / (1 + np.exp(-margin))

        return score


def train(examples: list[tuple[np.ndarray, int]], bits: int, alpha: float = 1.0, beta: float = 1.0, l1: float = 4.0, l2: float = 1.0, passes: int = 3) -> Weights:
    """FTRL-proximal over examples (feature indices, label), in their order; the bias is a
    coordinate of its own without L1."""
    z, n = np.zeros((1 << bits) + 1), np.zeros((1 << bits) + 1)
    bias = 1 << bits
    for _ in range(passes):
        for index, label in examples:
            at = np.append(index, bias)
            zi, ni = z[at], n[at]
            limit = np.full(len(at), l1)
            limit[-1] = 0.0
            w = np.where(np.abs(zi) <= limit, 0.0, (np.sign(zi) * limit - zi) / ((beta + np.sqrt(ni)) / alpha + l2))
            g = 1 / (1 + np.exp(-np.clip(w.sum(), -30, 30))) - label
            grown = ni + g * g
            z[at] = zi + g - (np.sqrt(grown) - np.sqrt(ni)) / alpha * w
            n[at] = grown
    limit = np.full(len(z), l1)
    limit[-1] = 0.0
    w = np.where(np.abs(z) <= limit, 0.0, (np.sign(z) * limit - z) / ((beta + np.sqrt(n)) / alpha + l2))
    kept = np.flatnonzero(w[:-1])
    return Weights(kept, w[kept].astype(np.float32), float(w[-1]), bits)


def held_out(id_col: Column) -> Column:
    return F.coalesce(F.crc32(id_col.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit(df: DataFrame, labels: DataFrame, sample: int = 12_000, bits: int = 20, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", learn_from: Column | None = None) -> Weights:
    """Weights from labelled rows of ``df``. Rows of each label are thinned separately to about half
    of ``sample``, and the prior they came with is restored in the bias."""
    ship(df.sparkSession)
    known = labels.filter(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("_id"), F.col(label_col).cast("int").alias("_label"))
    if learn_from is not None:
        known = known.filter(learn_from)
    known = known.groupBy("_id").agg(F.max("_label").alias("_label"))
    sizes = {r["_label"]: r["count"] for r in known.groupBy("_label").count().collect()}  # one row for each label
    half = sample // 2
    order = F.pmod(F.xxhash64("_id", F.lit("sample")), F.lit(1 << 30))
    bound = lambda label: int(min(1.0, half / max(1, sizes.get(label, 0))) * (1 << 30))
    few = known.filter(order < F.when(F.col("_label") == 1, bound(1)).otherwise(bound(0)))
    docs = documents(df, id_col, text_col).join(F.broadcast(few), F.col("doc_id") == F.col("_id"))  # about ``sample`` rows

    def featurise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            index, count = features(b.column("text"), bits)
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(count)]), pa.int32()), pa.array(index, pa.int32()))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("_label"), lists], ["id", "label", "index"])

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = [(mix(np.array([i], np.int64).view(np.uint64))[0], np.asarray(x.values), y) for b in batches for i, y, x in zip(b.column("id").to_pylist(), b.column("label").to_pylist(), b.column("index"))]
        seen.sort(key=lambda e: (int(e[0]), len(e[1])))
        w = train([(index, int(label == 1)) for _, index, label in seen], bits)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(w.index, -1), pa.int64()), pa.array(np.append(w.value, w.bias), pa.float64())], ["index", "value"])

    sampled = docs.mapInArrow(featurise, "id long, label int, index array<int>")
    got = sampled.repartition(1).mapInArrow(learn, "index long, value double").collect() if sizes else []  # 2**bits rows at most; L1 leaves some thousands
    if not got or 1 not in sizes:
        return Weights(np.zeros(0, np.int64), np.zeros(0, np.float32), -30.0, bits)
    pairs = sorted((r["index"], r["value"]) for r in got)
    kept = {label: bound(label) / (1 << 30) * n for label, n in sizes.items()}
    ones, zeros = sizes[1], sum(n for label, n in sizes.items() if label != 1)
    prior = np.log(ones / max(1, zeros)) - np.log(max(1e-9, kept[1]) / max(1e-9, sum(n for label, n in kept.items() if label != 1)))
    return Weights(np.array([i for i, _ in pairs[1:]], np.int64), np.array([v for _, v in pairs[1:]], np.float32), float(pairs[0][1] + (prior if zeros else 0.0)), bits)


def add_scores(df: DataFrame, weights: Weights, text_col: str = "text", score_col: str = "score") -> DataFrame:
    """``df`` with a column ``score_col`` (0 to 1) for the whole of each text."""
    ship(df.sparkSession)
    shared = df.sparkSession.sparkContext.broadcast(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = shared.value.scorer()
        for b in slices(batches, text_col):
            texts = b.column(text_col)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(score(texts))], [*b.schema.names, score_col])

    return df.mapInArrow(run, f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in df.schema)}, `{score_col}` double")
