"""Single-source similarity, end to end."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import bounds
from ..functions.sampling import SamplingPlan
from ..operators import meeting, walks
from ..operators.pairs import meets_of_decaying
from ..sources.graphs import Graph
from ..sources.tables import keep


def finish(scores: DataFrame, source: int, nodes: DataFrame | None = None) -> DataFrame:
    """Adds the source itself with 1; with ``nodes``, all others with 0."""
    spark = scores.sparkSession
    own = spark.createDataFrame([(source, source, 1.0)], "source long, node long, score double")
    full = scores.select(F.col("source").cast("long"), "node", "score").filter(F.col("node") != source).union(own)
    if nodes is None:
        return full
    return nodes.select(F.col("id").alias("node")).join(full, "node", "left").select(F.lit(source).cast("long").alias("source"), "node", F.coalesce("score", F.lit(0.0)).alias("score"))


def fused_meets(g: Graph, plan: SamplingPlan, source: int, seed: int, adj: DataFrame | None = None, targets: DataFrame | None = None, fast: bool = False) -> DataFrame:
    """Meetings found while walking. All walk only as long as their partner, the source's walk of the
    same pair, and end where they meet it. Only walks still going are moved, in one exchange a step,
    and what is sent to all is a step of one node's walks."""
    adj = walks.prepared(g) if adj is None else adj
    own_start = g.nodes.filter(F.col("id") == source).select("id")
    starts = None if targets is None else targets.select("id").union(own_start)
    lengths = keep(walks.pre_permuted(g, plan, seed, own_start).select("pair", F.col("planned_len").alias("source_len")), "source-lengths")
    ahead = walks.pre_permuted(g, plan, seed, starts).join(F.broadcast(lengths), "pair").select("start", "walk_no", "pair", "planned_len", "source_len", F.col("start").alias("node"), "deg")
    found = None
    most = lengths.agg(F.max("source_len")).first()[0] or 0
    edges = adj.select("node", "rk", "nbr", F.col("nbr_deg").alias("to_deg"))
    for k in range(1, most + 1):
        ahead = ahead.filter(F.least("planned_len", "source_len") >= k).withColumn("rk", walks.choice(seed, F.lit(k), F.col("deg"), fast)).filter("rk is not null")
        step = keep(ahead.join(edges, ["node", "rk"]).select("start", "walk_no", "pair", "planned_len", "source_len", F.col("nbr").alias("node"), F.col("to_deg").alias("deg")), "frontier")
        own = step.filter(F.col("start") == source).select("pair", F.col("node").alias("own_node"))
        seen = step.join(F.broadcast(own), "pair")  # a pair whose source walk has stopped has no one to meet
        met = (F.col("own_node") == F.col("node")) & (F.col("start") != source)
        hits = seen.filter(met).select("pair", F.lit(source).cast("long").alias("source"), "source_len", F.col("start").alias("target"), F.col("planned_len").alias("target_len"))
        found = hits if found is None else found.union(hits)
        ahead = seen.filter(~met).drop("own_node")
        if k % 4 == 0 and ahead.isEmpty():
            break
    if found is None:
        return ahead.limit(0).select("pair", F.lit(source).cast("long").alias("source"), "source_len", F.col("start").alias("target"), F.col("planned_len").alias("target_len"))
    return found


def starts_of(g: Graph, sources: list[int], longest: int, adj: DataFrame) -> DataFrame:
    """id: ``walks.can_meet`` of these sources, as far as they are nodes."""
    return walks.can_meet(g, g.nodes.filter(F.col("id").isin(sources)).select("id"), longest, adj)


def labelled_tuples(g: Graph, plan: SamplingPlan, seed: int, strategy: str = "stepwise", labels: str = "pre_permuted", adj: DataFrame | None = None, layout: str = "merged", starts: DataFrame | None = None) -> DataFrame:
    """(pair, step, node, walk_len, start) of all the plan's walks, written once."""
    adj = walks.prepared(g) if adj is None else adj
    steps = walks.generate(g, plan, seed, strategy, layout, starts, adj)
    if labels == "pre_permuted":
        pairs = walks.pre_permuted(g, plan, seed, starts)
    else:
        pairs = walks.labels(walks.planned(g, plan, seed, starts), seed, labels)
    return keep(walks.tuples(steps, pairs), "tuples")


def single_source(
    g: Graph,
    source: int,
    c: float = 0.6,
    eps: float = 0.1,
    seed: int = 0,
    n: int | None = None,
    delta: float | None = None,
    scope: str = "per_node",
    truncation: str = "drop",
    rounding: str = "ceil",
    normalization: str = "ideal",
    strategy: str = "stepwise",
    labels: str = "pre_permuted",
    method: str = "fused",
    targets: DataFrame | None = None,
    zeros: bool = False,
) -> DataFrame:
    """source, node, score by walks of planned lengths. ``method`` "fused" finds meetings while
    walking; the others generate all walks, label and decompose them and detect meetings in the
    tuples. ``targets`` (column id): only these nodes are scored. Walks that cannot meet the
    source's, whatever the draws, are not walked."""
    plan, adj = SamplingPlan.create(n or g.size(), c, eps, delta, scope, truncation, rounding), walks.prepared(g)
    starts = starts_of(g, [source], plan.longest, adj)
    if targets is not None:
        starts = starts.join(targets.select("id").union(starts.filter(F.col("id") == source)).distinct(), "id", "left_semi")
    if method == "fused":
        meets = fused_meets(g, plan, source, seed, adj, starts)
    else:
        meets = meeting.detect(labelled_tuples(g, plan, seed, strategy, labels, adj, starts=starts), source, method)
    return finish(meeting.aggregate(meets, plan, normalization), source, g.nodes if zeros else None)


def warm_up(g: Graph, source: int, c: float = 0.6, eps: float = 0.1, seed: int = 0, n: int | None = None, strategy: str = "stepwise", coin: str = "planned") -> DataFrame:
    """source, node, score by decaying walks: the j-th of the source against the j-th of each node;
    the share that meets. ``coin`` "per_step" tosses at every step instead of drawing lengths."""
    n = n or g.size()
    pairs, most = math.ceil(bounds.warm_up_walks(n, eps)), math.ceil(bounds.warm_up_length(n, eps, c))
    adj = walks.prepared(g)
    starts = starts_of(g, [source], most, adj)
    return finish(meeting.fraction(meets_of_decaying(g, source, pairs, c, seed, most, strategy, coin, starts, adj), pairs), source)


def multi_source(g: Graph, sources: DataFrame, plan: SamplingPlan, seed: int = 0, normalization: str = "ideal", tuples: DataFrame | None = None) -> DataFrame:
    """source, node, score for several sources (column id) over the same walks."""
    tuples = labelled_tuples(g, plan, seed) if tuples is None else tuples
    ids = sources.select(F.col("id").alias("source")).distinct()
    own = tuples.join(ids, F.col("start") == F.col("source"), "left_semi").select("pair", "step", "node", F.col("start").alias("source"), F.col("walk_len").alias("source_len"))
    rest = tuples.select("pair", "step", "node", F.col("start").alias("target"), F.col("walk_len").alias("target_len"))
    meets = rest.join(own, ["pair", "step", "node"]).filter("source != target").select(*meeting.MEETS).distinct()
    own_scores = ids.select("source", F.col("source").alias("node"), F.lit(1.0).alias("score"))
    return meeting.aggregate(meets, plan, normalization).union(own_scores)


def top_k(scores: DataFrame, k: int) -> DataFrame:
    return scores.filter("source != node").orderBy(F.desc("score"), "node").limit(k)


def top_k_per_source(scores: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("source").orderBy(F.desc("score"), "node")
    return scores.filter("source != node").withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def at_least(scores: DataFrame, threshold: float) -> DataFrame:
    return scores.filter((F.col("score") >= threshold) & (F.col("source") != F.col("node")))


def rank(scores: DataFrame) -> DataFrame:
    order = Window.partitionBy("source").orderBy(F.desc("score"), "node")
    return scores.withColumns({"rank": F.rank().over(Window.partitionBy("source").orderBy(F.desc("score"))), "place": F.row_number().over(order)})


def assign_to_seeds(scores: DataFrame) -> DataFrame:
    """node, seed: the source it is most similar to (ties to the smaller)."""
    best = F.max(F.struct(F.col("score"), (-F.col("source")).alias("s")))
    return scores.groupBy("node").agg(best.alias("b")).select("node", (-F.col("b.s")).alias("seed"), F.col("b.score").alias("score"))


def join_attributes(scores: DataFrame, nodes: DataFrame) -> DataFrame:
    return scores.join(nodes.withColumnRenamed("id", "node"), "node", "left")


def choose_strategy(n: int, m: int, executor_bytes: int, edge_bytes: int = 40) -> str:
    """Walks where they start if an executor holds all edges; stepwise if it holds a word for each
    node; else by stitching."""
    if m * edge_bytes <= executor_bytes // 8:
        return "local"
    return "stepwise" if n * 8 <= executor_bytes else "stitched"
