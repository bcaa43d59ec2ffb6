"""Connected components of an edge table, by alternating large and small stars.

Each round ties a node's larger neighbours to its least neighbour, then its
smaller neighbours likewise; the edges end as stars around each component's
least node. Groups are folded by partial aggregation, never gathered; each round
is written to the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, stash


def connected_components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """node, root (the least node reachable) for every node that an edge (a, b: long) joins to
    another; roots themselves are left out."""
    now = stash(_oriented(edges), "edges")
    state = _state(now)
    for _ in range(most_rounds):
        if not state[0]:
            break
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.filter("u != v").distinct()
        floor = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(floor, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v"))
        small = small.union(large.join(floor, "u").select("u", F.col("m").alias("v")))
        old, now = now, stash(_oriented(small.select(F.col("u").alias("a"), F.col("v").alias("b"))), "edges")
        discard(old)
        before, state = state, _state(now)
        if before == state:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
    if state[0]:
        raise RuntimeError(f"components did not settle in {most_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root"))


def _oriented(edges: DataFrame) -> DataFrame:
    """Distinct edges from the larger node u to the smaller v."""
    return edges.filter("a != b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()


def _state(edges: DataFrame) -> tuple[int, int]:
    row = edges.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(20,0)")), F.lit(0))).first()
    return row[0], int(row[1])
