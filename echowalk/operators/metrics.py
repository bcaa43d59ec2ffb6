"""Accuracy and cost measures."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def compared(est: DataFrame, exact: DataFrame) -> DataFrame:
    """source, node, est, exact, err of all nodes but the source; a missing score is 0."""
    a = est.select("source", "node", F.col("score").alias("est"))
    b = exact.select("source", "node", F.col("score").alias("exact"))
    both = a.join(b, ["source", "node"], "full").filter("source != node")
    zero = lambda x: F.coalesce(x, F.lit(0.0))
    return both.select("source", "node", zero("est").alias("est"), zero("exact").alias("exact"), (zero("est") - zero("exact")).alias("err"))


def max_abs_error(est: DataFrame, exact: DataFrame) -> DataFrame:
    return compared(est, exact).groupBy("source").agg(F.max(F.abs("err")).alias("max_abs_error"))


def error_summary(est: DataFrame, exact: DataFrame) -> DataFrame:
    """source, n, max_abs_error, mean_abs_error, bias, p50, p90, p99."""
    at = lambda q: F.percentile(F.abs("err"), F.lit(q))
    return compared(est, exact).groupBy("source").agg(F.count(F.lit(1)).alias("n"), F.max(F.abs("err")).alias("max_abs_error"), F.avg(F.abs("err")).alias("mean_abs_error"), F.avg("err").alias("bias"), at(0.5).alias("p50"), at(0.9).alias("p90"), at(0.99).alias("p99"))


def failure_rate(run: Callable[[int], DataFrame], exact: DataFrame, seeds: list[int], eps: float) -> DataFrame:
    """runs, failed_runs, failed_nodes (share of nodes and runs) for errors over ``eps``."""
    out = None
    for s in seeds:
        part = compared(run(s), exact).select(F.lit(s).alias("seed"), (F.abs("err") > eps).cast("int").alias("bad"))
        out = part if out is None else out.union(part)
    by_seed = out.groupBy("seed").agg(F.max("bad").alias("any"), F.sum("bad").alias("bad"), F.count(F.lit(1)).alias("n"))
    return by_seed.agg(F.count(F.lit(1)).alias("runs"), F.sum("any").alias("failed_runs"), (F.sum("bad") / F.sum("n")).alias("failed_nodes"))


def ranking(est: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """source, precision, ndcg, kendall_tau at k; ties go to smaller nodes."""
    both = compared(est, exact)
    order = lambda c: F.row_number().over(Window.partitionBy("source").orderBy(F.desc(c), "node"))
    ranked = both.withColumns({"re": order("est"), "rx": order("exact")})
    hits = ranked.filter((F.col("re") <= k) & (F.col("rx") <= k)).groupBy("source").agg((F.count(F.lit(1)) / F.lit(k)).alias("precision"))
    gain = lambda r: F.sum(F.when(F.col(r) <= k, F.col("exact") / F.log2(F.col(r) + 1)).otherwise(0.0))
    ndcg = ranked.groupBy("source").agg((gain("re") / gain("rx")).alias("ndcg"))
    top = ranked.filter(F.col("rx") <= k).select("source", "node", "re", "rx")
    other = top.select("source", F.col("re").alias("re2"), F.col("rx").alias("rx2"))
    pairs = top.join(other, "source").filter("rx < rx2").groupBy("source").agg(F.avg(F.when(F.col("re") < F.col("re2"), 1.0).otherwise(-1.0)).alias("kendall_tau"))
    return ndcg.join(hits, "source", "left").join(pairs, "source", "left").select("source", F.coalesce("precision", F.lit(0.0)).alias("precision"), "ndcg", "kendall_tau")


def half_width(samples: int, delta: float) -> float:
    return math.sqrt(math.log(2 / delta) / (2 * samples))


def report(runs: DataFrame, by: list[str], value: str, mode: str = "rollup", sets: list[list[str]] | None = None) -> DataFrame:
    """Means of ``value`` by groups and their totals: rollup, cube or given grouping sets."""
    agg = [F.count(F.lit(1)).alias("n"), F.avg(value).alias("mean")]
    if mode == "rollup":
        return runs.rollup(*by).agg(*agg)
    if mode == "cube":
        return runs.cube(*by).agg(*agg)
    return runs.groupingSets([[F.col(c) for c in s] for s in sets], *by).agg(*agg)


def partition_sizes(df: DataFrame) -> DataFrame:
    """part, rows: the space each task holds."""
    return df.groupBy(F.spark_partition_id().alias("part")).agg(F.count(F.lit(1)).alias("rows"))


def messages_per_walk(meets_all: DataFrame) -> DataFrame:
    """raw and unique messages, and the most that one pair of walks sends."""
    per = meets_all.groupBy("pair", "source", "target").agg(F.count(F.lit(1)).alias("raw"))
    return per.agg(F.sum("raw").alias("raw"), F.count(F.lit(1)).alias("unique"), F.max("raw").alias("most"))
