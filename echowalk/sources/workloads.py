"""Graphs over the given tables. Ids of two kinds of nodes are kept apart as 2k and 2k + 1."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.primitives import global_rank
from .graphs import Graph, from_edges
from .tables import keep, read


def _nodes(*kinds: tuple[DataFrame, str]) -> DataFrame:
    """Nodes (id, key) of each kind."""
    out = None
    for df, kind in kinds:
        part = df.select("id", F.lit(kind).alias("kind"), F.col("key").cast("string").alias("key"))
        out = part if out is None else out.union(part)
    return out


def _two_sided(pairs: DataFrame, left: str, right: str, names: tuple[str, str], directed: bool) -> Graph:
    pairs = pairs.filter(F.col(left).isNotNull() & F.col(right).isNotNull()).select(F.col(left).alias("l"), F.col(right).alias("r")).distinct()
    nodes = _nodes((pairs.select((F.col("l") * 2).alias("id"), F.col("l").alias("key")).distinct(), names[0]), (pairs.select((F.col("r") * 2 + 1).alias("id"), F.col("r").alias("key")).distinct(), names[1]))
    return from_edges(pairs.select((F.col("l") * 2).alias("src"), (F.col("r") * 2 + 1).alias("dst")), directed=directed, nodes=nodes)


def part_supplier(spark: SparkSession, sf_dir: str) -> Graph:
    return _two_sided(read(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey"), "l_partkey", "l_suppkey", ("part", "supplier"), False)


def customer_part(spark: SparkSession, sf_dir: str, directed: bool = False) -> Graph:
    orders = read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("k"), "o_custkey")
    lines = read(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k"), "l_partkey")
    return _two_sided(orders.join(lines, "k"), "o_custkey", "l_partkey", ("customer", "part"), directed)


def _close(k: int, margin: float = 1e-8):
    """Of a block of asking vectors and one of others: for each that asks those within ``margin`` of its
    k-th best cosine in the block, which is far more than products by matrices are off."""

    def run(table: pa.Table) -> pa.Table:
        ids, asks = table["id"].to_numpy(), table["asks"].to_numpy(zero_copy_only=False)
        x = table["v"].combine_chunks().flatten().to_numpy().reshape(len(ids), -1)
        x = x / np.sqrt((x * x).sum(1, keepdims=True))
        other, out = ids[~asks], []
        for at in range(0, int(asks.sum()), 1024):
            own = ids[asks][at : at + 1024]
            c = x[asks][at : at + 1024] @ x[~asks].T
            c[own[:, None] == other] = -np.inf
            if not len(other):
                continue
            least = np.partition(c, max(0, len(other) - k), axis=1)[:, max(0, len(other) - k)]
            i, j = np.nonzero((c >= least[:, None] - margin) & (c > -np.inf))
            out.append((own[i], other[j], c[i, j]))
        q, r, about = (np.concatenate(z) for z in zip(*out)) if out else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        return pa.table({"id": q, "id2": r, "about": about})

    return run


def embedding_knn(spark: SparkSession, sf_dir: str, k: int = 2, block: int = 4096) -> Graph:
    """Each vector to its k nearest by cosine (rounded to 9 digits, ties to smaller ids). Blocks of vectors
    meet by matrix products, all with all; what comes close to a vector's k-th best is then computed
    and rounded one by one. Of equal vectors only the k + 1 smallest ids can be near any. Vectors that
    are null, hold null or have no finite length above 0 meet all one by one."""
    v = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    v = v.withColumn("size", F.sqrt(dot(F.col("v"), F.col("v"))))
    fit = F.coalesce((F.col("size") > 0) & (F.col("size") < float("inf")) & F.col("id").isNotNull(), F.lit(False))
    v = keep(v.withColumn("fit", fit), "vectors")
    usual, odd = v.filter("fit"), v.filter("not fit")
    first = Window.partitionBy("v").orderBy("id")
    others = usual.withColumn("nth", F.row_number().over(first)).filter(F.col("nth") <= k + 1)
    blocks = max(1, -(-usual.count() // block))
    place, every = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    width = F.size("v").alias("width")
    met = usual.select("id", "v", width, F.lit(True).alias("asks"), place.alias("a"), every.alias("b")).union(others.select("id", "v", width, F.lit(False), every, place))
    close = keep(met.groupBy("a", "b", "width").applyInArrow(_close(k), "id long, id2 long, about double"), "close")
    ranked = close.withColumn("kth", F.sort_array(F.collect_list("about").over(Window.partitionBy("id")), False))
    pairs = close.select("id", "id2") if blocks == 1 else ranked.filter(F.col("about") >= F.try_element_at("kth", F.least(F.lit(k), F.size("kth"))) - 1e-8).select("id", "id2")
    own = v.select("id", "v", "size")
    pairs = pairs.join(own, "id").join(own.select(F.col("id").alias("id2"), F.col("v").alias("v2"), F.col("size").alias("size2")), "id2").select("id", "v", "size", "id2", "v2", "size2")
    if not odd.isEmpty() or v.select(width).distinct().count() > 1:
        pair = lambda a, b: a.select("id", "v", "size").join(b.select(F.col("id").alias("id2"), F.col("v").alias("v2"), F.col("size").alias("size2"), F.size("v").alias("w2")), F.col("id") != F.col("id2"))
        uneven = pair(usual, usual).filter(F.size("v") != F.col("w2"))
        pairs = pairs.union(pair(odd, v).drop("w2")).union(pair(usual, odd).drop("w2")).union(uneven.drop("w2"))
    pairs = pairs.select("id", "id2", F.round(F.try_divide(dot(F.col("v"), F.col("v2")), F.col("size") * F.col("size2")), 9).alias("cosine"))
    near = pairs.withColumn("rn", F.row_number().over(Window.partitionBy("id").orderBy(F.desc("cosine"), "id2"))).filter(F.col("rn") <= k)
    return from_edges(near, "id", "id2", nodes=_nodes((v.select("id", F.col("id").alias("key")), "vector")))


def page_links(spark: SparkSession, sf_dir: str, directed: bool = True, level: str = "page") -> Graph:
    """Pages (or, at level "host", their hosts) to the targets of their links. Keys are numbered in
    their order."""
    links = read(spark, sf_dir, "pages").select("page_id", "url", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("target"))
    if level == "host":
        links = links.withColumn("page", F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1))
    # written, as pages are large and their links are read several times
    links = keep(links.drop("url").distinct(), "links")
    if level == "host":
        hosts = keep(global_rank(links.select(F.col("page").alias("key")).distinct(), ["key"]), "hosts").select("key", (F.col("rank") * 2).alias("id"))
        links = links.join(hosts.select(F.col("key").alias("page"), F.col("id").alias("src")), "page")
        pages = hosts
    else:
        links = links.withColumn("src", F.col("page_id") * 2)
        pages = links.select(F.col("src").alias("id"), F.col("page_id").alias("key")).distinct()
    targets = keep(global_rank(links.select(F.col("target").alias("key")).distinct(), ["key"]), "targets").select("key", (F.col("rank") * 2 + 1).alias("id"))
    edges = links.join(targets.select(F.col("key").alias("target"), F.col("id").alias("dst")), "target").select("src", "dst")
    g = from_edges(edges, directed=directed, nodes=_nodes((pages, level), (targets, "target")))
    return Graph(keep(g.nodes, "nodes"), keep(g.edges, "edges"), directed)


def user_transition(spark: SparkSession, sf_dir: str, start: str | None = None, end: str | None = None, gap: str | None = None, events: DataFrame | None = None) -> Graph:
    """Each event's user to the next event's, by (ts, event_id), without loops. The next event is
    found within a day; a day's last is tied to the first of the next day that has events."""
    e = (read(spark, sf_dir, "events") if events is None else events).select("event_id", "ts", "user_id")
    if start:
        e = e.filter(F.col("ts") >= F.lit(start).cast("timestamp"))
    if end:
        e = e.filter(F.col("ts") < F.lit(end).cast("timestamp"))
    e = e.withColumn("day", F.to_date("ts"))
    within = Window.partitionBy("day").orderBy("ts", "event_id")
    following = e.withColumns({"to": F.lead("user_id").over(within), "to_ts": F.lead("ts").over(within)})
    first = e.groupBy("day").agg(F.min(F.struct("ts", "event_id", "user_id")).alias("f"))
    border = first.select("day", F.lead("f").over(Window.orderBy("day")).alias("f"))  # a row for each day
    tied = following.join(F.broadcast(border), "day", "left").select("user_id", "ts", F.coalesce("to", "f.user_id").alias("to"), F.coalesce("to_ts", "f.ts").alias("to_ts"))
    tied = tied.filter("to is not null and user_id != to")
    if gap:
        tied = tied.filter(F.col("to_ts") <= F.col("ts") + F.expr(f"INTERVAL {gap}"))
    return from_edges(tied, "user_id", "to")


def nation_trade(spark: SparkSession, sf_dir: str, min_price: float = 300_000.0, priority: str | None = "1-URGENT", min_qty: float = 45.0) -> Graph:
    """The customer's nation to the supplier's, over large urgent orders."""
    orders = read(spark, sf_dir, "orders").filter(F.col("o_totalprice") > min_price)
    if priority:
        orders = orders.filter(F.col("o_orderpriority") == priority)
    lines = read(spark, sf_dir, "lineitem").filter(F.col("l_quantity") >= min_qty)
    joined = orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).join(read(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(read(spark, sf_dir, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    nations = read(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("id"), F.col("n_name").alias("key"))
    return from_edges(joined, "c_nationkey", "s_nationkey", nodes=_nodes((nations, "nation")))


def _kept_keys(df: DataFrame, key: str, unit: str, least: int, most: int | None = None) -> DataFrame:
    counted = df.groupBy(key).agg(F.count_distinct(unit).alias("n")).filter(F.col("n") >= least)
    return counted.filter(F.col("n") <= most) if most else counted


def doc_lines(spark: SparkSession, sf_dir: str, min_docs: int = 2) -> Graph:
    """Documents to the lines (trimmed) that at least ``min_docs`` documents have."""
    lines = read(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line")).filter("line != ''").distinct()
    kept = _kept_keys(lines, "line", "doc_id", min_docs)
    numbered = keep(global_rank(kept.select("line"), ["line"]), "lines")
    return _two_sided(lines.join(numbered, "line").select("doc_id", "rank"), "doc_id", "rank", ("document", "line"), False)


def conversation_tokens(spark: SparkSession, sf_dir: str, role: str = "user", max_df: int | None = None) -> Graph:
    """Conversations to the words of ``role`` that two or more (and at most ``max_df``, if given) of them have."""
    words = read(spark, sf_dir, "conversations").filter(F.col("role") == role).select("conv_id", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("word")).filter("word != ''").distinct()
    numbered = keep(global_rank(_kept_keys(words, "word", "conv_id", 2, max_df).select("word"), ["word"]), "words")
    return _two_sided(words.join(numbered, "word").select("conv_id", "rank"), "conv_id", "rank", ("conversation", "word"), False)


CORNERS = {
    "siblings": [(1, 2), (1, 3)],
    "star": [(1, 2), (1, 3), (1, 4), (1, 5)],
    "cycle": [(1, 2), (2, 3), (3, 4), (4, 5), (5, 1)],
    "chain": [(1, 2), (2, 3)],
    "two_levels": [(1, 3), (2, 4), (5, 1), (5, 2)],
    "repeated": [(1, 3), (1, 3), (2, 3), (1, 4)],
    "self_loop": [(1, 1), (1, 2), (2, 2)],
    "bipartite_2_3": [(a, b) for a in (1, 2) for b in (3, 4, 5)] + [(b, a) for a in (1, 2) for b in (3, 4, 5)],
}


def corner(spark: SparkSession, name: str) -> Graph:
    return from_edges(spark.createDataFrame(CORNERS[name], "src long, dst long"))
