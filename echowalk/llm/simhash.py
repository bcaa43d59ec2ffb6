"""SimHash near-duplicates by multi-index hashing.

A fingerprint is cut into segments; two that differ in at most ``distance`` bits
differ in at most ``distance // segments`` bits of some segment. Each distinct
fingerprint is entered in a table once for each segment and looks up the Hamming
ball of that radius around its own segment; matches are verified on all bits.
Lookups that meet in one key are settled in blocks, and each block reports a
spanning forest of its verified links, never all of them. Of a pair one bit
apart only the one whose bit is clear asks.

Defined results: null and empty texts have no words, the fingerprint zero, and
link like any other; rows that agree in id and text count as one document, and
every such row is returned; null ids come after all others; an empty table
gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Words, byte_table, distinct, documents, numbered, ship, slices, stash
from .components import connected_components


def _fingerprints(shingle: int, seed: int):
    table = byte_table(lower=True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh64_digest

        for batch in slices(batches):
            w = Words(batch.column("text"), table)
            data, first = w.data.tobytes(), w.first
            count = np.diff(first)
            # a shingle starts at every word that has enough words of its text behind it, or at the first of a short text
            size = np.where(count > 0, np.maximum(count - shingle + 1, 1), 0)
            base = np.concatenate([[0], np.cumsum(size)])
            at = np.repeat(first[:-1] - base[:-1], size) + np.arange(base[-1])
            to = np.minimum(at + shingle, np.repeat(first[1:], size)) - 1
            digests = b"".join([xxh64_digest(data[s:e], seed) for s, e in zip(w.start[at].tolist(), w.end[to].tolist())])
            bits = np.unpackbits(np.frombuffer(digests, np.uint8)).reshape(-1, 64)
            out = np.zeros(len(count), np.uint64)
            full = np.flatnonzero(size)
            if len(full):
                ones = np.add.reduceat(bits, base[:-1][full], axis=0, dtype=np.int32)
                out[full] = np.packbits(2 * ones > size[full, None], axis=1).view(">u8").ravel()
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(out.view(np.int64))], ["doc_id", "fp"])

    return run


def fingerprints(df: DataFrame, shingle: int = 3, seed: int = 42, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and 64-bit fingerprint ``fp`` (as a signed long): a bit is set if it is in over half
    of the XXH64 hashes of the word shingles of the text."""
    ship(df.sparkSession)
    return documents(df, id_col, text_col).mapInArrow(_fingerprints(shingle, seed), "doc_id long, fp long")


def _segments(count: int) -> list[tuple[int, int]]:
    """(shift, bits) of each segment."""
    edge = [64 * k // count for k in range(count + 1)]
    return [(a, b - a) for a, b in zip(edge, edge[1:])]


def _value(fp: Column, shift: int, bits: int) -> Column:
    return F.shiftrightunsigned(fp, shift).bitwiseAND(F.lit((1 << bits) - 1))


def _lookups(value: Column, bits: int, radius: int) -> Column:
    """The table entry ``value``, and the other keys it has to ask: with one bit changed, of two
    partners the one with the bit clear asks; from two bits on the whole ball is enumerated."""
    if radius == 0:
        return F.array(value)
    masks = F.array(*(F.lit(1 << k).cast("long") for k in range(bits)))
    if radius == 1:
        clear = F.filter(masks, lambda m: m.bitwiseAND(value) == 0)
        return F.concat(F.array(value), F.transform(clear, lambda m: m.bitwiseOR(value)))
    ball = F.array(value)
    for _ in range(radius):
        ball = F.array_distinct(F.concat(ball, F.flatten(F.transform(ball, lambda v: F.transform(masks, lambda m: m.bitwiseXOR(v))))))
    return ball


def forest(fps: np.ndarray, distance: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the links between distinct fingerprints: each one reached is compared
    with those not reached yet, which leaves one link for each."""
    left, a, b = fps, [], []
    while len(left):
        ahead, left = [left[:1]], left[1:]
        while ahead and len(left):
            front = ahead.pop()
            for x in front:
                near = np.bitwise_count(left ^ x) <= distance
                if near.any():
                    hit, left = left[near], left[~near]
                    a.append(np.full(len(hit), x))
                    b.append(hit)
                    ahead.append(hit)
    none = np.zeros(0, fps.dtype)
    return (np.concatenate(a), np.concatenate(b)) if a else (none, none)


def _settle(segments: list[tuple[int, int]], distance: int, few: int = 8):
    """Links within runs of equal (key, salt) of sorted rows."""
    shifts = np.array([s for s, _ in segments], np.uint64)
    masks = np.array([(1 << b) - 1 for _, b in segments], np.uint64)

    def links(key: np.ndarray, salt: np.ndarray, segment: np.ndarray, fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        new = np.concatenate([[True], (key[1:] != key[:-1]) | (salt[1:] != salt[:-1]) | (segment[1:] != segment[:-1])])
        start = np.flatnonzero(new)
        size = np.diff(np.concatenate([start, [len(key)]]))
        own = ((fp >> shifts[segment]) & masks[segment]) == key.view(np.uint64)
        live = (size > 1) & np.logical_or.reduceat(own, start)
        a, b = [], []
        small = live & (size <= few)
        for step in range(1, few):
            runs = small & (size > step)
            if not runs.any():
                break
            reach = np.repeat(start[runs], size[runs] - step) + _within(size[runs] - step)
            x, y = fp[reach], fp[reach + step]
            near = (np.bitwise_count(x ^ y) <= distance) & (x != y)
            a.append(x[near])
            b.append(y[near])
        for s, n in zip(start[live & ~small], size[live & ~small]):
            x, y = forest(distinct(fp[s : s + n]), distance)
            a.append(x)
            b.append(y)
        none = np.zeros(0, np.uint64)
        return np.concatenate([none, *a]), np.concatenate([none, *b])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            rows = tuple(np.asarray(batch.column(c)) for c in ("segment", "key", "salt", "fp"))
            last = (rows[0] == rows[0][-1]) & (rows[1] == rows[1][-1]) & (rows[2] == rows[2][-1])
            cut = len(last) - int(np.argmin(last[::-1])) if not last.all() else 0
            held.append(tuple(r[:cut] for r in rows) if cut else rows)
            if cut:
                yield done(held)
                held = [tuple(r[cut:] for r in rows)]
        if held:
            yield done(held)

    def done(held: list[tuple]) -> pa.RecordBatch:
        segment, key, salt, fp = (np.concatenate(c) for c in zip(*held))
        a, b = links(key, salt, segment, fp.view(np.uint64)) if len(key) else (np.zeros(0, np.uint64),) * 2
        return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["a", "b"])

    return run


def _within(sizes: np.ndarray) -> np.ndarray:
    """0, 1, ... for each of the sizes in turn."""
    return np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)


def fingerprint_links(fps: DataFrame, distance: int = 3, segments: int = 2, block: int = 2048) -> DataFrame:
    """Links (a, b) between distinct fingerprints (column fp) that join all those connected by steps
    of at most ``distance`` bits. A key with over ``block`` table entries is dealt out by pairs of
    blocks, as are the keys its entries ask."""
    cuts = _segments(segments)
    radius = distance // segments
    parts = [fps.select(F.lit(k).alias("segment"), "fp", _value(F.col("fp"), *cut).alias("own")) for k, cut in enumerate(cuts)]
    asked = [p.select("segment", "fp", F.explode(_lookups(F.col("own"), cut[1], radius)).alias("key")) for p, cut in zip(parts, cuts)]
    table, rows = parts[0], asked[0]
    for p, q in zip(parts[1:], asked[1:]):
        table, rows = table.union(p), rows.union(q)
    crowded = table.groupBy("segment", "own").count().filter(F.col("count") > block)
    hot = [crowded.filter(F.col("segment") == k).select("segment", F.explode(_lookups(F.col("own"), cut[1], radius)).alias("key"), "count") for k, cut in enumerate(cuts)]
    for h in hot[1:]:
        hot[0] = hot[0].union(h)
    sizes = stash(hot[0].groupBy("segment", "key").agg(F.sum("count").alias("n")), "crowded-keys")
    if sizes.isEmpty():
        rows = rows.withColumn("salt", F.lit(0).cast("long"))
    else:
        blocks = F.coalesce(F.ceil(F.col("n") / block), F.lit(1)).cast("long")
        mine = F.pmod(F.xxhash64("fp"), F.col("blocks"))
        pair = lambda j: F.least(mine, j) * (1 << 20) + F.greatest(mine, j)
        rows = rows.join(sizes, ["segment", "key"], "left").withColumn("blocks", blocks)
        rows = rows.select("segment", "key", "fp", F.explode(F.transform(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1), pair)).alias("salt"))
    rows = rows.select("segment", "key", "salt", "fp").repartition("segment", "key", "salt").sortWithinPartitions("segment", "key", "salt")
    return rows.mapInArrow(_settle(cuts, distance), "a long, b long")


def near_components(df: DataFrame, shingle: int = 3, distance: int = 3, seed: int = 42, segments: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fp, component_id (the least doc_id reachable over links) for every row of ``df``."""
    docs = stash(fingerprints(df, shingle, seed, id_col, text_col), "fingerprints")
    # the least id of a fingerprint stands for it; one that only null ids have gets a number of its own
    spare = F.col("fp").bitwiseAND(F.lit((1 << 62) - 1)).bitwiseOR(F.lit(1 << 62))
    nodes = stash(docs.groupBy("fp").agg(F.min("doc_id").alias("least")).select("fp", F.coalesce("least", spare).alias("node")), "nodes")
    links = stash(fingerprint_links(nodes.select("fp"), distance, segments), "links")
    edges = links.join(nodes.select(F.col("fp").alias("a"), F.col("node").alias("na")), "a").join(nodes.select(F.col("fp").alias("b"), F.col("node").alias("nb")), "b")
    roots = connected_components(edges.select(F.col("na").alias("a"), F.col("nb").alias("b")))
    by_fp = nodes.join(roots, "node", "left").select("fp", F.coalesce("root", "node").alias("component"))
    real = F.when(F.col("component") < (1 << 62), F.col("component"))
    return docs.join(by_fp, "fp").select("doc_id", "fp", real.alias("component_id"))


def keep_representatives(df: DataFrame, shingle: int = 3, distance: int = 3, seed: int = 42, segments: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows of ``df``, all columns, one for each component of texts linked by ``near_components``' rule:
    that of the least id. Rows are told by their own key, so ids may repeat or be null."""
    df = numbered(df)
    made = stash(fingerprints(df, shingle, seed, "_row", text_col), "fingerprints")
    lead = F.min(F.struct(F.col(id_col).isNull().alias("none"), F.col(id_col).alias("id"), "_row")).alias("lead")
    nodes = df.select("_row", id_col).join(made.select(F.col("doc_id").alias("_row"), "fp"), "_row")
    nodes = stash(nodes.groupBy("fp").agg(lead), "nodes")
    links = stash(fingerprint_links(nodes.select("fp"), distance, segments), "links")
    roots = connected_components(links).withColumnRenamed("node", "fp")
    best = nodes.join(roots, "fp", "left").groupBy(F.coalesce("root", "fp").alias("root")).agg(F.min("lead").alias("lead"))
    return df.join(best.select(F.col("lead._row").alias("_row")), "_row", "left_semi").drop("_row")
