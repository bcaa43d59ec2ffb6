"""Meetings of the source's walks with those of other nodes, and scores from them.

Two walks with the same pair number meet where they have the same node at the same
step. All methods give the same messages (pair, source, source_len, target,
target_len), each once, however often the walks meet.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.sampling import SamplingPlan
from .primitives import predecessor

MEETS = ("pair", "source", "source_len", "target", "target_len")


def _messages(df: DataFrame, once: bool) -> DataFrame:
    df = df.select(*MEETS)
    return df.distinct() if once else df


def by_join(tuples: DataFrame, source: int, once: bool = True, broadcast: bool = True) -> DataFrame:
    """The source's tuples, at most the steps of one node's plan, go to all others."""
    own = tuples.filter(F.col("start") == source).select("pair", "step", "node", F.col("start").alias("source"), F.col("walk_len").alias("source_len"))
    rest = tuples.filter(F.col("start") != source).select("pair", "step", "node", F.col("start").alias("target"), F.col("walk_len").alias("target_len"))
    return _messages(rest.join(F.broadcast(own) if broadcast else own, ["pair", "step", "node"]), once)


def by_predecessor(tuples: DataFrame, source: int, once: bool = True) -> DataFrame:
    """Within equal (pair, step, node), sorted with the source first, each tuple takes the last
    source tuple before it."""
    is_source = F.col("start") == source
    frame = Window.partitionBy("pair", "step", "node").orderBy(is_source.desc(), "start").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    found = tuples.withColumn("p", F.last(F.when(is_source, F.struct("start", "walk_len")), ignorenulls=True).over(frame)).filter(~is_source & F.col("p").isNotNull())
    return _messages(found.select("pair", F.col("p.start").alias("source"), F.col("p.walk_len").alias("source_len"), F.col("start").alias("target"), F.col("walk_len").alias("target_len")), once)


def by_global_predecessor(tuples: DataFrame, source: int, once: bool = True, check_pair: bool = True) -> DataFrame:
    """The same over one globally sorted list; a predecessor counts if pair, step and node agree.
    ``check_pair`` off is a control: neighbours of another pair then match wrongly."""
    marked = tuples.withColumn("rest", F.when(F.col("start") == source, 0).otherwise(1))
    found = predecessor(marked, ["pair", "step", "node", "rest", "start", "walk_len"], F.col("rest") == 0, ["pair", "step", "node", "start", "walk_len"]).filter("rest = 1 and pred is not null")
    same = (F.col("pred.step") == F.col("step")) & (F.col("pred.node") == F.col("node"))
    if check_pair:
        same = same & (F.col("pred.pair") == F.col("pair"))
    return _messages(found.filter(same).select("pair", F.col("pred.start").alias("source"), F.col("pred.walk_len").alias("source_len"), F.col("start").alias("target"), F.col("walk_len").alias("target_len")), once)


METHODS = {"broadcast_join": by_join, "predecessor": by_predecessor, "global_predecessor": by_global_predecessor}


def detect(tuples: DataFrame, source: int, method: str = "broadcast_join", **options) -> DataFrame:
    return METHODS[method](tuples, source, **options)


def aggregate(meets: DataFrame, plan: SamplingPlan, normalization: str = "ideal", distinct: bool = False) -> DataFrame:
    """source, node, score. Meetings are counted by pair of lengths first. "ideal" weighs a meeting
    with the lengths' ideal over actual numbers and 1/z; "unbiased" corrects that for the number of
    pairs; "plain" is the share of pairs that meet."""
    if distinct:
        meets = meets.distinct()
    counted = meets.groupBy("source", "target", "source_len", "target_len").agg(F.count(F.lit(1)).alias("n"))
    if normalization == "plain":
        weight = F.lit(1.0 / plan.expected_total())
    else:
        share = F.array(*(F.lit(s) for s in plan.shares()))
        base = plan.z if normalization == "ideal" else plan.z**2 / plan.expected_total()
        if normalization not in ("ideal", "unbiased"):
            raise ValueError(normalization)
        weight = F.element_at(share, F.col("source_len") + 1) * F.element_at(share, F.col("target_len") + 1) / F.lit(base)
    return counted.groupBy("source", F.col("target").alias("node")).agg(F.sum(weight * F.col("n")).alias("score"))


def fraction(meets: DataFrame, pairs: int) -> DataFrame:
    """source, node, score: the share of ``pairs`` pairs that meet."""
    counted = meets.select("source", "target", "pair").distinct().groupBy("source", F.col("target").alias("node")).agg(F.count(F.lit(1)).alias("n"))
    return counted.select("source", "node", (F.col("n") / F.lit(float(pairs))).alias("score"))
