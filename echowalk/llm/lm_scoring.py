"""Cross-entropy difference of a target and a background n-gram model.

Both are interpolated bigram models over one vocabulary, all words of all documents
(or, if asked, the most frequent ones and one class for all others), and a mark for
the text's start.
They are counted over all documents (background) and all target documents, and
smoothed alike. A document's score is the mean over its words of the loss under
the target model less the loss under the background model: below zero, it is
nearer to the target.

Words and bigrams are counted under hashes of 62 bits in buckets that grow in number
with the input and stay distributed. Texts come in blocks; a block sends
each bucket its distinct keys, sorted and compressed, and gets their counts over all
blocks back, so a frequent key crosses the exchange once a block. With
a vocabulary of given size the counts are dense and sent to the executors.

Defined results: a text without words has null losses; null text is empty; rows
that repeat are counted and scored each time; without target documents the
target model is uniform over the vocabulary; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, byte_table, documents, mix, ship, slices, stash, task_id, word_hashes

_TABLE = byte_table(lower=True)


def _count_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    hashes, counts, held = [], [], 0

    def done() -> pa.RecordBatch:
        key, at = np.unique(np.concatenate(hashes), return_inverse=True)
        return pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(np.bincount(at, weights=np.concatenate(counts)).astype(np.int64))], ["word", "n"])

    for batch in slices(batches):
        key, n = np.unique(word_hashes(Words(batch.column("text"), _TABLE)), return_counts=True)
        hashes.append(key)
        counts.append(n)
        held += len(key)
        if held > 2_000_000:
            yield done()
            hashes, counts, held = [], [], 0
    if hashes:
        yield done()


def vocabulary(docs: DataFrame, size: int) -> np.ndarray:
    """Sorted hashes of the ``size`` most frequent words of all documents."""
    totals = docs.select("text").mapInArrow(_count_words, "word long, n long").groupBy("word").agg(F.sum("n").alias("n"))
    top = totals.orderBy(F.desc("n"), "word").limit(size).collect()
    return np.sort(np.array([r["word"] for r in top], np.int64).view(np.uint64))


def word_ids(w: Words, words: np.ndarray) -> np.ndarray:
    """Places in the vocabulary; len(words): another word."""
    h = word_hashes(w)
    at = np.searchsorted(words, h)
    return np.where((at < len(words)) & (words[np.minimum(at, max(0, len(words) - 1))] == h), at, len(words)) if len(words) else np.zeros(len(h), np.int64)


def _pairs(w: Words, ids: np.ndarray, size: int) -> np.ndarray:
    """A bigram's cell for every word: its predecessor (``size + 1`` at the text's start) and itself."""
    before = np.concatenate([[size + 1], ids[:-1]])
    before[w.first[:-1][np.diff(w.first) > 0]] = size + 1
    return before[: len(ids)] * (size + 1) + ids


def count_bigrams(docs: DataFrame, words: np.ndarray, block: int = 1 << 16) -> tuple[np.ndarray, np.ndarray]:
    """Background and target counts (predecessor x word) over all of ``docs`` (text, target)."""
    size = len(words)
    cells = (size + 2) * (size + 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((2, -(-cells // block) * block), np.int64)
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def add_up() -> None:
            for k, x in enumerate(zip(*held)):
                total[k] += np.bincount(np.concatenate(x), minlength=total.shape[1])
            held.clear()

        for batch in slices(batches):
            target = np.asarray(batch.column("target"))
            w = Words(batch.column("text"), _TABLE)
            pair = _pairs(w, word_ids(w, words), size)
            good = np.repeat(target, np.diff(w.first))
            held.append((pair, pair[good]))
            if sum(len(p) for p, _ in held) > 4_000_000:
                add_up()
        add_up()
        pack = zstandard.ZstdCompressor(level=3).compress
        parts = [(k, pack(np.ascontiguousarray(total[:, k * block : (k + 1) * block]).tobytes())) for k in range(total.shape[1] // block)]
        yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in parts], pa.int32()), pa.array([c for _, c in parts], pa.binary())], ["part", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict[int, np.ndarray] = {}
        unpack, pack = zstandard.ZstdDecompressor().decompress, zstandard.ZstdCompressor(level=3).compress
        for b in batches:
            for part, c in zip(b.column("part").to_pylist(), b.column("counts")):
                found = np.frombuffer(unpack(c.as_py()), np.int64)
                totals[part] = totals[part] + found if part in totals else found
        yield pa.RecordBatch.from_arrays([pa.array(list(totals), pa.int32()), pa.array([pack(t.tobytes()) for t in totals.values()], pa.binary())], ["part", "counts"])

    sums = docs.mapInArrow(run, "part int, counts binary").repartition("part").mapInArrow(add, "part int, counts binary")
    out = np.zeros((2, -(-cells // block) * block), np.int64)
    for r in sums.collect():  # one row for each block of the vocabulary's square
        out[:, r["part"] * block : (r["part"] + 1) * block] = np.frombuffer(zstandard.ZstdDecompressor().decompress(r["counts"]), np.int64).reshape(2, block)
    return tuple(x[:cells].reshape(size + 2, size + 1) for x in out)


def losses(counts: np.ndarray, weight: float = 0.7, add: float = 0.5) -> np.ndarray:
    """-log2 of the interpolated probability of each word after each predecessor. Predecessors never
    seen leave all to the smoothed unigram model."""
    seen = counts.sum(1, keepdims=True)
    single = (counts.sum(0) + add) / (counts.sum() + add * counts.shape[1])
    share = np.where(seen > 0, weight, 0.0)
    return -np.log2(share * counts / np.maximum(seen, 1) + (1 - share) * single)


_START = np.uint64(0x2545F4914F6CDD1D)
_WORD, _BEFORE, _GRAM = (np.uint64(k) for k in range(3))  # kinds of counted keys, in their last bits


def _key(h: np.ndarray, kind: np.uint64) -> np.ndarray:
    return mix(h + kind) & ~np.uint64(3) | kind


class Counted:
    """Sorted distinct keys of texts, and for every word the places of three of them: its own, that of
    its predecessor as one, and that of the pair."""

    def __init__(self, texts: pa.Array):
        w = Words(texts, _TABLE)
        self.first = w.first
        h = word_hashes(w)
        before = np.concatenate([[_START], h[:-1]])[: len(h)].astype(np.uint64)
        before[w.first[:-1][np.diff(w.first) > 0]] = _START
        parts = [np.unique(_key(x, kind), return_inverse=True) for x, kind in ((h, _WORD), (before, _BEFORE), (mix(before) + h, _GRAM))]
        every = np.concatenate([keys for keys, _ in parts])
        order = np.argsort(every)
        place = np.empty(len(every), np.int64)
        place[order] = np.arange(len(every))
        base = np.cumsum([0, *(len(keys) for keys, _ in parts)])
        self.keys, self.at = every[order], [place[k + own] for k, (_, own) in zip(base, parts)]

    def counts(self, good: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """How often each key is there, and in texts that are ``good``."""
        of_word = np.repeat(good, np.diff(self.first)).astype(np.float64)
        return tuple(sum(np.bincount(at, x, len(self.keys)) for at in self.at).astype(np.int64) for x in (None, of_word))

    def losses(self, n: np.ndarray, good: np.ndarray, tokens: tuple[int, int], words: int, weight: float, add: float) -> list[np.ndarray]:
        """Mean loss of each text under the model of all counts ``n`` and that of ``good``."""
        out, size = [], np.diff(self.first)
        for count, total in ((good, tokens[1]), (n, tokens[0])):
            word, before, pair = (count[at] for at in self.at)
            share = np.where(before > 0, weight, 0.0)
            loss = -np.log2(share * pair / np.maximum(before, 1) + (1 - share) * (word + add) / (total + add * (words + 1)))
            upto = np.concatenate([[0.0], np.cumsum(loss)])
            out.append((upto[self.first[1:]] - upto[self.first[:-1]]) / np.maximum(size, 1))
        return out


def _packed(*columns: np.ndarray) -> bytes:
    """Columns of 64-bit numbers, each byte of a number with the others of its place."""
    planes = [np.ascontiguousarray(c.astype(np.uint64).view(np.uint8).reshape(-1, 8).T).tobytes() for c in columns]
    return zstandard.ZstdCompressor(level=1).compress(b"".join(planes))


def _unpacked(data: bytes, columns: int) -> list[np.ndarray]:
    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8).reshape(columns, 8, -1)
    return [np.ascontiguousarray(c.T).view(np.uint64).ravel() for c in raw]


_BLOCK = "block long, n_words long, ids array<long>, good array<boolean>, sizes array<long>, texts binary"


def _blocks(size: int):
    """Texts in blocks of ``size`` bytes, or one text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=3).compress
        number, held, bytes_held = task_id() << 32, [], 0

        def done() -> pa.RecordBatch:
            texts = [t for _, _, part in held for t in part]
            words = sum(len(t.split()) for t in texts)  # for the number of buckets alone
            row = [[number], [words], [[i for ids, _, _ in held for i in ids]], [[g for _, good, _ in held for g in good]], [[len(t) for t in texts]], [pack(b"".join(texts))]]
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(row, (pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.bool_()), pa.list_(pa.int64()), pa.binary()))], ["block", "n_words", "ids", "good", "sizes", "texts"])

        for batch in slices(batches):
            texts = batch.column("text").cast(pa.binary()).to_pylist()
            held.append((batch.column("doc_id").to_pylist(), batch.column("target").to_pylist(), texts))
            bytes_held += sum(map(len, texts))
            if bytes_held >= size:
                yield done()
                number, held, bytes_held = number + 1, [], 0
        if held:
            yield done()

    return run


def _texts(b: pa.RecordBatch, row: int) -> pa.Array:
    off = np.concatenate([[0], np.cumsum(np.asarray(b.column("sizes")[row].values))]).astype(np.int64)
    data = zstandard.ZstdDecompressor().decompress(b.column("texts")[row].as_py())
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(off) - 1, [None, pa.py_buffer(off), pa.py_buffer(data)])


def _edges(keys: np.ndarray, buckets: int) -> np.ndarray:
    """Where each bucket of equal ranges starts among sorted keys, and the end."""
    return np.searchsorted(keys, np.array([(k << 64) // buckets for k in range(buckets)], np.uint64)).tolist() + [len(keys)]


def _ask(buckets: int):
    """The keys and counts of each block, by bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row in range(b.num_rows):
                own = Counted(_texts(b, row))
                n, good = own.counts(np.asarray(b.column("good")[row].values))
                edge = _edges(own.keys, buckets)
                parts = [(k, s, e) for k, (s, e) in enumerate(zip(edge, edge[1:])) if e > s]
                data = [_packed(np.diff(own.keys[s:e], prepend=np.uint64(0)), n[s:e], good[s:e]) for _, s, e in parts]
                block = b.column("block")[row].as_py()
                yield pa.RecordBatch.from_arrays([pa.array([block] * len(parts), pa.int64()), pa.array([k for k, _, _ in parts], pa.int32()), pa.array(data, pa.binary())], ["block", "bucket", "data"])

    return run


def _answer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by bucket: each block's keys' counts over all blocks; and as block -1 what all
    words of the bucket sum up to."""

    def done(rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
        asked = [_unpacked(data, 3) for _, _, data in rows]
        keys, of = np.unique(np.concatenate([np.cumsum(k, dtype=np.uint64) for k, _, _ in asked]), return_inverse=True)
        n, good = (np.bincount(of, np.concatenate([x[c] for x in asked]).astype(np.float64)).astype(np.int64) for c in (1, 2))
        edge = np.cumsum([0, *(len(k) for k, _, _ in asked)]).tolist()
        told = [_packed(n[of[s:e]], good[of[s:e]]) for s, e in zip(edge, edge[1:])]
        word = keys & np.uint64(3) == _WORD
        sums = np.array([word.sum(), n[word].sum(), good[word].sum()])
        bucket = [rows[0][0]] * (len(rows) + 1)
        return pa.RecordBatch.from_arrays([pa.array([r[1] for r in rows] + [-1], pa.int64()), pa.array(bucket, pa.int32()), pa.array(told + [None], pa.binary()), pa.array([None] * len(rows) + [sums.tolist()], pa.list_(pa.int64()))], ["block", "bucket", "data", "sums"])

    held: list[tuple[int, int, bytes]] = []
    for b in batches:
        for row in zip(b.column("bucket").to_pylist(), b.column("block").to_pylist(), b.column("data").to_pylist()):
            if held and held[0][0] != row[0]:
                yield done(held)
                held = []
            held.append(row)
    if held:
        yield done(held)


def _score(tokens: tuple[int, int], words: int, weight: float, add: float):
    """Of rows sorted by block and bucket, a block's texts first: the losses of its texts."""

    def done(ids: pa.Array, texts: pa.Array, told: list[bytes]) -> pa.RecordBatch:
        own = Counted(texts)
        n, good = (np.concatenate(c).astype(np.int64) for c in zip(*(_unpacked(t, 2) for t in told))) if told else (np.zeros(0, np.int64),) * 2
        size = np.diff(own.first)
        target, background = own.losses(n, good, tokens, words, weight, add)
        columns = (target, background, target - background)
        return pa.RecordBatch.from_arrays([ids, pa.array(size, pa.int64()), *(pa.array(x, mask=size == 0) for x in columns)], ["doc_id", "n_words", "target_loss", "background_loss", "score"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for b in batches:
            for row, (bucket, data) in enumerate(zip(b.column("bucket").to_pylist(), b.column("data").to_pylist())):
                if bucket < 0:
                    if held:
                        yield done(*held)
                    held = (b.column("ids")[row].values, _texts(b, row), [])
                else:
                    held[2].append(data)
        if held:
            yield done(*held)

    return run


def score_by_blocks(marked: DataFrame, weight: float = 0.7, add: float = 0.5, block: int = 8 << 20, keys_a_bucket: int = 1_000_000) -> DataFrame:
    """Scores of ``marked`` (doc_id, text, target) by counts of all words and bigrams. A block of texts
    asks for each of its distinct keys once; a bucket of keys adds up what all blocks have
    and answers them; both stay distributed, and their number grows with the input."""
    blocks = stash(marked.mapInArrow(_blocks(block), _BLOCK), "blocks")
    total = blocks.agg(F.count(F.lit(1)).alias("blocks"), F.sum("n_words").alias("n")).first()
    buckets = max(1, -(-(total["n"] or 0) // keys_a_bucket))
    asked = blocks.mapInArrow(_ask(buckets), "block long, bucket int, data binary")
    told = stash(asked.repartition(-(-buckets // 2), "bucket").sortWithinPartitions("bucket").mapInArrow(_answer, "block long, bucket int, data binary, sums array<long>"), "answers")
    sums = told.filter("block = -1").agg(*(F.coalesce(F.sum(F.col("sums")[k]), F.lit(0)) for k in range(3))).first()
    none = lambda of: [F.lit(None).cast(t).alias(c) for c, t in of]
    texts = [("ids", "array<long>"), ("sizes", "array<long>"), ("texts", "binary")]
    rows = blocks.select("block", F.lit(-1).alias("bucket"), *none([("data", "binary")]), *(c for c, _ in texts))
    rows = rows.unionByName(told.filter("block >= 0").select("block", "bucket", "data", *none(texts)))
    rows = rows.repartition(max(1, total["blocks"]), "block").sortWithinPartitions("block", "bucket")
    return rows.mapInArrow(_score((sums[1], sums[2]), sums[0], weight, add), "doc_id long, n_words long, target_loss double, background_loss double, score double")


def score_documents(df: DataFrame, target: DataFrame, vocabulary_size: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, target_loss, background_loss, score (their difference) for every row of
    ``df``; ``target``: ids (doc_id) of the target documents. ``vocabulary_size``: words that are told
    apart, by dense tables; all words if None."""
    ship(df.sparkSession)
    docs = documents(df, id_col, text_col)
    marks = target.select(F.col("doc_id").alias("_id")).filter("_id is not null").distinct().withColumn("_target", F.lit(True)).hint("merge")  # the same plan at every size
    marked = docs.join(marks, F.col("doc_id") == F.col("_id"), "left").select("doc_id", "text", F.coalesce("_target", F.lit(False)).alias("target"))
    if vocabulary_size is None:
        return score_by_blocks(marked)
    words = vocabulary(docs, vocabulary_size)
    counts = count_bigrams(marked, words)
    size = len(words)
    shared = df.sparkSession.sparkContext.broadcast((words, np.stack([losses(counts[1]), losses(counts[0])]).astype(np.float32)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, table = shared.value
        for batch in slices(batches):
            w = Words(batch.column("text"), _TABLE)
            pair = _pairs(w, word_ids(w, words), size)
            n = np.diff(w.first)
            means = []
            for losses_of in table.reshape(2, -1):
                total = np.concatenate([[0.0], np.cumsum(losses_of[pair], dtype=np.float64)])
                means.append((total[w.first[1:]] - total[w.first[:-1]]) / np.maximum(n, 1))
            empty = n == 0
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n), *(pa.array(x, mask=empty) for x in (*means, means[0] - means[1]))], ["doc_id", "n_words", "target_loss", "background_loss", "score"])

    return docs.mapInArrow(run, "doc_id long, n_words long, target_loss double, background_loss double, score double")
