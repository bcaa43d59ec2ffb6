"""Near duplicates by the Jaccard similarity of word shingles: MinHash bands bring
candidates together, the shingle sets themselves decide.

Texts with equal shingle sets are one node. Of each node ``bands`` keys are made,
each of ``rows`` least hashes; nodes that share a key meet in a bucket. Buckets
with the same members are settled once, those of over ``block`` members in
blocks, each with some leaders of the bucket; members that this leaves outside the
bucket's largest component then meet all others, block by block. Each meeting reports a
spanning forest of its verified links, never all of them. A link is verified by the whole sets, so no pair below the threshold is
joined. A pair of similarity s shares no key with probability (1 - s**rows)**bands:
3e-6 at 0.8 with the defaults, and less above.

Defined results: null and empty texts have no shingles and equal each other; a
text shorter than a shingle is one; null ids come after all others; rows that
repeat are rows of their own, of which one stays; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SpanHash, Words, byte_table, mix, numbered, ship, slices, stash, word_hashes
from .components import connected_components

_TABLE = byte_table(lower=True)


def shingle_sets(texts: pa.Array, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashes of each text's word shingles, one text after another, and each text's count."""
    w = Words(texts, _TABLE)
    count = np.diff(w.first)
    size = np.where(count > 0, np.maximum(count - shingle + 1, 1), 0)
    base = np.concatenate([[0], np.cumsum(size)])
    if not base[-1]:
        return np.zeros(0, np.uint64), size
    at = np.repeat(w.first[:-1] - base[:-1], size) + np.arange(base[-1])
    to = np.minimum(at + shingle, np.repeat(w.first[1:], size)) - 1
    h, doc = SpanHash(word_hashes(w)).of(at, to), np.repeat(np.arange(len(size)), size)
    order = np.lexsort((h, doc))
    h, doc = h[order], doc[order]
    new = np.concatenate([[True], (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])])
    return h[new], np.bincount(doc[new], minlength=len(size))


def _sketches(shingle: int, bands: int, rows: int, seed: int):
    draw = np.random.default_rng(seed).integers(0, 2**63, (bands * rows, 2), dtype=np.uint64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            h, size = shingle_sets(batch.column("text"), shingle)
            full = np.flatnonzero(size)
            start = (np.cumsum(size) - size)[full]
            s0, s1 = np.zeros(len(size), np.uint64), np.zeros(len(size), np.uint64)
            keys = np.zeros((len(full), bands), np.uint64)
            if len(full):
                s0[full] = np.add.reduceat(mix(h), start)
                s1[full] = np.add.reduceat(mix(h ^ np.uint64(0xD6E8FEB86659FD93)), start)
                for k, (flip, times) in enumerate(draw):
                    keys[:, k // rows] = mix(keys[:, k // rows] ^ np.minimum.reduceat((h ^ flip) * (times | np.uint64(1)), start)) + np.uint64(k + 1)
            off = np.concatenate([[0], np.cumsum(np.where(size > 0, bands, 0))]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(off), pa.array(keys.view(np.int64).ravel()))
            yield pa.RecordBatch.from_arrays([batch.column("row"), batch.column("id"), pa.array(s0.view(np.int64)), pa.array(s1.view(np.int64)), lists], ["row", "id", "s0", "s1", "keys"])

    return run


def forest(h: np.ndarray, size: np.ndarray, least: float) -> list[tuple[int, int]]:
    """A spanning forest of the pairs of sets with a Jaccard similarity of ``least`` or more: each set
    reached is compared with those not reached yet."""
    ids = np.unique(h, return_inverse=True)[1]
    start = np.cumsum(size) - size
    mark = np.zeros(len(ids), np.int32)
    open_, out = np.ones(len(size), bool), []
    for root in range(len(size)):
        ahead = [root] if open_[root] else []
        open_[root] = False
        while ahead:
            x = ahead.pop()
            own = ids[start[x] : start[x] + size[x]]
            mark[own] = 1
            both = np.add.reduceat(mark[ids], start)
            mark[own] = 0
            near = np.flatnonzero(open_ & (both + 1e-9 >= least * (size + size[x] - both)))
            open_[near] = False
            out += [(x, int(y)) for y in near]
            ahead += near.tolist()
    return out


def _settle(shingle: int, least: float):
    """Verified links within runs of equal (bucket, salt) of sorted rows."""

    def done(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        rows = pa.Table.from_batches(held).combine_chunks().to_batches()[0]
        bucket, salt, node = (np.asarray(rows.column(c)) for c in ("bucket", "salt", "node"))
        edge = np.flatnonzero(np.concatenate([[True], (bucket[1:] != bucket[:-1]) | (salt[1:] != salt[:-1]), [True]]))
        parts = [shingle_sets(part.column("text"), shingle) for part in slices(iter([rows]))]
        h, size = (np.concatenate(c) for c in zip(*parts))
        at = np.concatenate([[0], np.cumsum(size)])
        links = [(node[s + x], node[s + y]) for s, e in zip(edge, edge[1:]) if e - s > 1 for x, y in forest(h[at[s] : at[e]], size[s:e], least)]
        a, b = zip(*links) if links else ((), ())
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            bucket, salt = np.asarray(batch.column("bucket")), np.asarray(batch.column("salt"))
            other = np.flatnonzero((bucket != bucket[-1]) | (salt != salt[-1]))
            cut = int(other[-1]) + 1 if len(other) else 0
            if not cut and held and (held[-1].column("bucket")[-1].as_py(), held[-1].column("salt")[-1].as_py()) != (bucket[0], salt[0]):
                yield done(held)
                held = []
            if cut:
                yield done([*held, batch.slice(0, cut)])
                held = []
            held.append(batch.slice(cut))
        if held:
            yield done(held)

    return run


def near_links(nodes: DataFrame, texts: DataFrame, shingle: int, least: float, block: int, leaders: int = 16) -> DataFrame:
    """Verified links (a, b) that join all nodes connected by candidates; ``nodes``: node, keys. Of a
    bucket of over ``block`` members each block first meets ``leaders`` of the bucket; then those
    not yet in its largest component meet each other and the component, block by block."""
    keyed = nodes.select("node", F.explode("keys").alias("bucket"))
    shared = keyed.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("node")).alias("members")).filter("n > 1")
    once = stash(shared.groupBy("n", "members").agg(F.min("bucket").alias("bucket")).select("bucket", "n"), "buckets")
    place, blocks = F.xxhash64("node"), lambda n: F.ceil(F.col(n) / block).cast("long")

    def settled(rows: DataFrame) -> DataFrame:
        met = rows.join(texts.select(F.col("row").alias("node"), "text"), "node").select("bucket", "salt", "node", "text")
        return met.repartition("bucket", "salt").sortWithinPartitions("bucket", "salt").mapInArrow(_settle(shingle, least), "a long, b long")

    rows = keyed.join(once.filter(F.col("n") <= block), "bucket").select("bucket", F.lit(0).cast("long").alias("salt"), "node")
    crowded = once.filter(F.col("n") > block)
    if crowded.isEmpty():
        return settled(rows)
    member = stash(keyed.join(crowded, "bucket").select("bucket", "n", "node"), "crowded")
    lead = member.groupBy("bucket", "n", F.pmod(F.xxhash64("node", F.lit(1)), F.lit(leaders)).alias("slot")).agg(F.min("node").alias("node"))
    dealt = member.select("bucket", (1 + F.pmod(place, blocks("n"))).alias("salt"), "node")
    dealt = dealt.union(lead.select("bucket", F.explode(F.sequence(F.lit(1).cast("long"), blocks("n"))).alias("salt"), "node")).distinct()
    first = stash(settled(rows.union(dealt)), "links-of-blocks")
    grouped = member.join(connected_components(first), "node", "left").select("bucket", "n", "node", F.coalesce("root", "node").alias("of"))
    main = grouped.groupBy("bucket", "n", "of").count().groupBy("bucket", "n").agg(F.max(F.struct("count", "of")).alias("main"))
    main = main.select("bucket", F.col("main.of").alias("main"), F.col("main.count").alias("in_main"), (F.col("n") - F.col("main.count")).alias("others")).filter("others > 0")
    apart = grouped.join(main, "bucket").withColumns({"rest": blocks("others"), "body": blocks("in_main"), "inside": F.col("of") == F.col("main")})
    own = F.pmod(place, F.when(F.col("inside"), F.col("body")).otherwise(F.col("rest")))
    apart = apart.withColumn("own", own)
    upto = lambda n: F.sequence(F.lit(0).cast("long"), F.col(n) - 1)
    across = lambda rest, body: -1 - (rest * (1 << 24) + body)
    among = F.transform(upto("rest"), lambda j: F.least(F.col("own"), j) * (1 << 24) + F.greatest(F.col("own"), j))
    salts = F.when(F.col("inside"), F.transform(upto("rest"), lambda j: across(j, F.col("own")))).otherwise(F.concat(among, F.transform(upto("body"), lambda j: across(F.col("own"), j))))
    return first.union(settled(apart.select("bucket", F.explode(salts).alias("salt"), "node")))


def keep_representatives(df: DataFrame, shingle: int = 5, least: float = 0.8, bands: int = 24, rows: int = 4, seed: int = 42, block: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows of ``df``, all columns, one for each component of texts that are joined by similarities
    of ``least`` or more: that of the least id."""
    ship(df.sparkSession)
    df = numbered(df)
    texts = df.select(F.col("_row").alias("row"), F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    made = stash(texts.mapInArrow(_sketches(shingle, bands, rows, seed), "row long, id long, s0 long, s1 long, keys array<long>"), "sketches")
    lead = F.min(F.struct(F.col("id").isNull().alias("none"), "id", "row")).alias("lead")
    nodes = stash(made.groupBy("s0", "s1").agg(lead, F.first("keys").alias("keys")).select(F.col("lead.row").alias("node"), "lead", "keys"), "nodes")
    links = stash(near_links(nodes.select("node", "keys"), texts, shingle, least, block), "links")
    roots = connected_components(links)
    best = nodes.join(roots, "node", "left").groupBy(F.coalesce("root", "node").alias("root")).agg(F.min("lead").alias("lead"))
    return df.join(best.select(F.col("lead.row").alias("_row")), "_row", "left_semi").drop("_row")
