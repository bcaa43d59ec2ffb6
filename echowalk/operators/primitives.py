"""Primitives of massively parallel computation on DataFrames: sort, global rank,
predecessor, owners. None of them puts all rows of a window into one task."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import keep

_LOCAL = (1 << 33) - 1


def sort(df: DataFrame, cols: list, partitions: int | None = None) -> DataFrame:
    """Globally sorted: ranges of keys, each sorted."""
    ranged = df.repartitionByRange(partitions, *cols) if partitions else df.repartitionByRange(*cols)
    return ranged.sortWithinPartitions(*cols)


def _placed(df: DataFrame, cols: list) -> DataFrame:
    """Sorted and written, with ``_part`` and ``_row`` (both from 0)."""
    at = F.monotonically_increasing_id()
    return keep(sort(df, cols).withColumn("_at", at).withColumns({"_part": F.shiftright("_at", 33), "_row": F.col("_at").bitwiseAND(F.lit(_LOCAL))}).drop("_at"), "sorted")


def global_rank(df: DataFrame, cols: list, rank: str = "rank") -> DataFrame:
    """Adds the place of each row (from 0) in the order of ``cols``: rows before it in its partition,
    and all rows of the partitions before."""
    placed = _placed(df, cols)
    sizes = placed.groupBy("_part").count()
    before = F.coalesce(F.sum("count").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = sizes.select("_part", before.alias("_before"))  # a row for each partition
    return placed.join(F.broadcast(offsets), "_part").withColumn(rank, F.col("_before") + F.col("_row")).drop("_part", "_row", "_before")


def predecessor(df: DataFrame, cols: list, label: Column, take: list[str], out: str = "pred") -> DataFrame:
    """Adds a struct of ``take`` from the nearest row before (or at) each row for which ``label``
    holds, in the order of ``cols``; null if there is none. A partition's last labelled row is
    carried over to those after it."""
    placed = _placed(df, cols).withColumn("_own", F.when(label, F.struct(*take)))
    running = Window.partitionBy("_part").orderBy("_row").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    lasts = placed.filter("_own is not null").groupBy("_part").agg(F.max_by("_own", "_row").alias("_last"))
    parts = placed.select("_part").distinct().join(lasts, "_part", "left")
    carry = F.last("_last", ignorenulls=True).over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1))
    carried = parts.select("_part", carry.alias("_carry"))  # a row for each partition
    found = placed.withColumn(out, F.last("_own", ignorenulls=True).over(running)).join(F.broadcast(carried), "_part", "left")
    return found.withColumn(out, F.coalesce(out, "_carry")).drop("_part", "_row", "_own", "_carry")


def scatter(df: DataFrame, machines: int, seed: int = 0) -> DataFrame:
    """Rows at random places: the model's initial placement."""
    cols = df.columns
    return df.repartition(machines, F.xxhash64(F.lit(seed), *cols))


def owner(node: Column, n: int, machines: int) -> Column:
    """The machine (from 1) that owns node 1..n."""
    return F.ceil(node * machines / n).cast("int")


def swap_shuffle(df: DataFrame, group: str, order: Column) -> DataFrame:
    """Permutes the rows of each group that sorting may have split over two partitions: a group's
    rows behind the border go to the partition where it begins, and each partition then numbers
    its groups (column ``pair``, from 1) by ``order``."""
    placed = _placed(df, [group])
    home = placed.groupBy(group).agg(F.min("_part").alias("_home"))
    moved = placed.join(home, group).repartition("_home", group)
    return moved.withColumn("pair", F.row_number().over(Window.partitionBy("_home", group).orderBy(order))).drop("_home", "_part", "_row")


def degrees_by_placeholder(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """node, degree (edges into it): edges and one placeholder a node are ranked together, and the
    gap between placeholders, less one, is the degree. A sentinel closes the last gap."""
    marks = nodes.select(F.col("id").alias("node"), F.lit(-(2**62)).cast("long").alias("nbr"))
    end = nodes.agg((F.coalesce(F.max("id"), F.lit(0)) + 1).alias("node")).select("node", F.lit(-(2**62)).cast("long").alias("nbr"))
    ranked = global_rank(edges.select(F.col("dst").alias("node"), F.col("src").alias("nbr")).union(marks).union(end), ["node", "nbr"])
    holders = global_rank(ranked.filter(F.col("nbr") == -(2**62)), ["rank"], "nth")
    following = holders.select((F.col("nth") - 1).alias("nth"), F.col("rank").alias("next"))
    return holders.join(following, "nth").select("node", (F.col("next") - F.col("rank") - 1).alias("degree"))
