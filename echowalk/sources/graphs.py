"""Graph tables: nodes(id, kind, key) and distinct edges(src, dst)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.primitives import global_rank
from .tables import keep


@dataclass(frozen=True)
class Graph:
    nodes: DataFrame
    edges: DataFrame
    directed: bool = True

    def size(self) -> int:
        return self.nodes.count()


def from_edges(df: DataFrame, src: str = "src", dst: str = "dst", directed: bool = True, drop_self_loops: bool = False, nodes: DataFrame | None = None) -> Graph:
    """Edges as a set: nulls and repeated rows go; undirected edges are kept both ways. Nodes are
    those of the edges unless given."""
    edges = df.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst")).filter("src is not null and dst is not null")
    if drop_self_loops:
        edges = edges.filter("src != dst")
    if not directed:
        edges = edges.union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    edges = edges.distinct()
    if nodes is None:
        ids = edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct()
        nodes = ids.select("id", F.lit("node").alias("kind"), F.col("id").cast("string").alias("key"))
    return Graph(nodes, edges, directed)


def reversed_graph(g: Graph) -> Graph:
    return Graph(g.nodes, g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")), g.directed)


def symmetrised(g: Graph) -> Graph:
    return from_edges(g.edges, directed=False, nodes=g.nodes)


def degrees(g: Graph, side: str = "in") -> DataFrame:
    """node, degree for every node."""
    by = "dst" if side == "in" else "src"
    counted = g.edges.groupBy(F.col(by).alias("node")).agg(F.count(F.lit(1)).alias("degree"))
    return g.nodes.select(F.col("id").alias("node")).join(counted, "node", "left").select("node", F.coalesce("degree", F.lit(0)).alias("degree"))


def dead_ends(g: Graph) -> DataFrame:
    """Nodes without in-neighbours: where walks stop."""
    return g.nodes.select(F.col("id").alias("node")).join(g.edges.select(F.col("dst").alias("node")), "node", "left_anti")


def ranked_adjacency(g: Graph) -> DataFrame:
    """node, rk (from 0, by neighbour), nbr, nbr_deg, node_deg: one row for each in-neighbour. A rank
    is the edge's global rank less that of its node's first edge, so no node's edges have to meet
    in one task, and a walker on a hub joins one of its rows only."""
    ranked = keep(global_rank(g.edges.select(F.col("dst").alias("node"), F.col("src").alias("nbr")), ["node", "nbr"]), "ranked")
    first = ranked.groupBy("node").agg(F.min("rank").alias("first"), F.count(F.lit(1)).alias("node_deg"))
    adj = ranked.join(first, "node").select("node", (F.col("rank") - F.col("first")).cast("int").alias("rk"), "nbr", F.col("node_deg").cast("int").alias("node_deg"))
    degree = first.select(F.col("node").alias("nbr"), F.col("node_deg").cast("int").alias("nbr_deg"))
    return adj.join(degree, "nbr", "left").select("node", "rk", "nbr", F.coalesce("nbr_deg", F.lit(0)).alias("nbr_deg"), "node_deg")


def filter_degree(g: Graph, low: int = 0, high: int | None = None, side: str = "in") -> Graph:
    kept = degrees(g, side).filter(F.col("degree") >= low)
    return induced(g, (kept.filter(F.col("degree") <= high) if high is not None else kept).select(F.col("node").alias("id")))


def induced(g: Graph, ids: DataFrame) -> Graph:
    ids = ids.select("id").distinct()
    edges = g.edges.join(ids.select(F.col("id").alias("src")), "src", "left_semi").join(ids.select(F.col("id").alias("dst")), "dst", "left_semi")
    return Graph(g.nodes.join(ids, "id", "left_semi"), edges.select("src", "dst"), g.directed)


def dense_ids(g: Graph) -> tuple[Graph, DataFrame]:
    """The graph with ids 1..n in the order of ids, and the map (old, id)."""
    numbered = keep(global_rank(g.nodes.select(F.col("id").alias("old"), "kind", "key"), ["old"], "rank"), "dense").withColumn("id", F.col("rank") + 1)
    to = numbered.select("old", "id")
    edges = g.edges.join(to.select(F.col("old").alias("src"), F.col("id").alias("s")), "src").join(to.select(F.col("old").alias("dst"), F.col("id").alias("d")), "dst")
    return Graph(numbered.select("id", "kind", "key"), edges.select(F.col("s").alias("src"), F.col("d").alias("dst")), g.directed), to


def union(a: Graph, b: Graph) -> Graph:
    return Graph(a.nodes.union(b.nodes).dropDuplicates(["id"]), a.edges.union(b.edges).distinct(), a.directed or b.directed)


def intersect(a: Graph, b: Graph) -> Graph:
    return Graph(a.nodes.join(b.nodes.select("id"), "id", "left_semi"), a.edges.intersect(b.edges), a.directed)


def subtract(a: Graph, b: Graph) -> Graph:
    return Graph(a.nodes, a.edges.exceptAll(b.edges), a.directed)


def windowed_edges(events: DataFrame, src: str, dst: str, ts: str, size: str, slide: str | None = None) -> DataFrame:
    """window_start, src, dst, n: edges of each tumbling or sliding window."""
    frame = F.window(ts, size, slide) if slide else F.window(ts, size)
    return events.groupBy(frame.alias("w"), F.col(src).alias("src"), F.col(dst).alias("dst")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("window_start"), "src", "dst", "n")
