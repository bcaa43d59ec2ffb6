"""Random walks along in-neighbours.

A walk of start v with number w takes its k-th step to the in-neighbour whose rank
is a draw of (v, w, k) modulo the degree, so every strategy gives the same walks.
Walks are kept in long form: steps(start, walk_no, planned_len, step, node); the
start itself is not a step. A walk at a node without in-neighbours stops there and
keeps its planned length.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import partial
from weakref import WeakKeyDictionary

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.rng import SPAN, draw, draws_local, fast_draw, uniform
from ..functions.sampling import SamplingPlan
from ..sources.graphs import Graph, degrees, ranked_adjacency
from ..sources.tables import keep

STEPS = ("start", "walk_no", "planned_len", "step", "node")
LOCAL_EDGES = 500_000  # above it no adjacency is sent to all: the driver holds it several times
_prepared: WeakKeyDictionary[Graph, DataFrame] = WeakKeyDictionary()
_sent: WeakKeyDictionary[DataFrame, object] = WeakKeyDictionary()


def prepared(g: Graph) -> DataFrame:
    """The ranked adjacency, written once for all steps and methods."""
    if g not in _prepared:
        _prepared[g] = keep(ranked_adjacency(g), "adjacency")
    return _prepared[g]


def reach(g: Graph, sources: DataFrame, longest: int, adj: DataFrame) -> DataFrame:
    """id, odd: what the sources (column id) reach along in-neighbours in up to ``longest`` steps, then
    what reaches that, told by the parity of the step (a source: 0)."""
    if adj.count() <= LOCAL_EDGES:
        return _reach_local(sources, longest, adj)
    edges = adj.select(F.col("node").alias("at"), F.col("nbr").alias("to"))
    seen = ahead = keep(sources.select("id", F.lit(0).alias("odd")).distinct(), "reached")
    for way in (edges, edges.select(F.col("to").alias("at"), F.col("at").alias("to"))):
        ahead, more = seen, False
        for _ in range(longest):
            found = ahead.join(way, F.col("id") == F.col("at")).select(F.col("to").alias("id"), (1 - F.col("odd")).alias("odd")).distinct()
            ahead = keep(found.join(seen, ["id", "odd"], "left_anti"), "reached")
            more = not ahead.isEmpty()
            if not more:
                break
            seen = seen.union(ahead)
        if not (g.directed or more):
            break  # closed, and the edges go both ways
    return seen


def to_all(adj: DataFrame) -> DataFrame:
    """The adjacency, sent to all in joins if it is small enough."""
    return F.broadcast(adj) if adj.count() <= LOCAL_EDGES else adj


def _reach_local(sources: DataFrame, longest: int, adj: DataFrame) -> DataFrame:
    """``reach`` where one machine holds the adjacency."""
    table = adj.select("node", "nbr").toArrow()
    own = np.array([r["id"] for r in sources.select("id").distinct().collect()], np.int64)
    ids, place = np.unique(np.concatenate([own, table["node"].to_numpy(), table["nbr"].to_numpy()]), return_inverse=True)
    node, nbr = np.split(place[len(own) :], 2)
    seen = np.zeros((2, len(ids)), bool)
    seen[0, place[: len(own)]] = True
    for at, to in ((node, nbr), (nbr, node)):
        ahead = seen.copy()
        for _ in range(longest):
            found = np.zeros_like(seen)
            for odd in (0, 1):
                found[1 - odd, to[ahead[odd][at]]] = True
            ahead = found & ~seen
            if not ahead.any():
                break
            seen |= ahead
    odd, at = np.nonzero(seen)
    return adj.sparkSession.createDataFrame(pa.table({"id": ids[at], "odd": odd.astype(np.int32)}), "id long, odd int")


def can_meet(g: Graph, sources: DataFrame, longest: int, adj: DataFrame | None = None) -> DataFrame:
    """id: the sources (column id), and all nodes whose walks may stand at the same step where a source's
    walk stands. Walks of other nodes meet none of the sources', whatever the draws."""
    return keep(reach(g, sources, longest, prepared(g) if adj is None else adj).filter("odd = 0").select("id"), "starts")


def _with_degree(g: Graph, starts: DataFrame | None) -> DataFrame:
    """start, deg for the given starts (column id), or all nodes."""
    d = degrees(g).select(F.col("node").alias("start"), F.col("degree").cast("int").alias("deg"))
    return d if starts is None else d.join(starts.select(F.col("id").alias("start")).distinct(), "start", "left_semi")


def planned(g: Graph, plan: SamplingPlan, seed: int, starts: DataFrame | None = None) -> DataFrame:
    """start, walk_no (from 1), planned_len, deg: the plan's walks of each start."""
    rows = _with_degree(g, starts).withColumn("lens", plan.lengths_of(F.col("start"), seed))
    return rows.select("start", "deg", F.posexplode("lens").alias("walk_no", "planned_len")).withColumn("walk_no", F.col("walk_no") + 1)


def decaying(g: Graph, per_node: int, c: float, seed: int, starts: DataFrame | None = None, most: int | None = None) -> DataFrame:
    """As ``planned``, with lengths of walks that stop with probability 1 - sqrt(c) before each step:
    geometric, drawn at once. Lengths beyond ``most`` are cut to it."""
    u = uniform(draw(seed, "length", F.col("start"), F.col("walk_no")))
    length = F.floor(F.ln(u) / F.lit(math.log(math.sqrt(c)))).cast("int")
    rows = _with_degree(g, starts).select("start", "deg", F.explode(F.sequence(F.lit(1), F.lit(per_node))).alias("walk_no"))
    return rows.withColumn("planned_len", F.least(length, F.lit(most)) if most is not None else length)


def choice(seed: int, step: Column, deg: Column, fast: bool = False) -> Column:
    bits = (fast_draw if fast else draw)(seed, "step", F.col("start"), F.col("walk_no"), step)
    return F.when(deg > 0, (bits % deg).cast("int"))


def stepwise(walkers: DataFrame, adj: DataFrame, longest: int, seed: int, fast: bool = False, coin: float | None = None) -> DataFrame:
    """One exchange of the walkers a step; each step's rows are written and start the next one.
    ``coin``: walk on with this probability at every step instead of up to a planned length."""
    ahead = walkers.select("start", "walk_no", "planned_len", F.lit(0).alias("step"), F.col("start").alias("node"), "deg")
    done, edges = [], adj.select("node", "rk", "nbr", F.col("nbr_deg").alias("deg"))
    for k in range(1, longest + 1):
        going = ahead.filter(F.col("planned_len") >= k)
        if coin is not None:
            going = going.filter(draw(seed, "coin", F.col("start"), F.col("walk_no"), F.lit(k)) < int(coin * SPAN))
        going = going.withColumn("rk", choice(seed, F.lit(k), F.col("deg"), fast)).filter("rk is not null").drop("deg", "step")
        ahead = keep(going.join(edges, ["node", "rk"]).select("start", "walk_no", "planned_len", F.lit(k).alias("step"), F.col("nbr").alias("node"), "deg"), "frontier")
        if ahead.isEmpty():
            break
        done.append(ahead.select(*STEPS))
    if not done:
        return ahead.limit(0).select(*STEPS)
    out = done[0]
    for d in done[1:]:
        out = out.union(d)
    return out


def stepwise_pairs(walkers: DataFrame, adj: DataFrame, longest: int, seed: int, fast: bool = False) -> DataFrame:
    """pair, step, node of labelled walkers of one start."""
    pairs = walkers.select("start", "walk_no", "pair")
    return stepwise(walkers, adj, longest, seed, fast).join(pairs, ["start", "walk_no"]).select("pair", "step", "node")


def to_tasks(adj: DataFrame, most_rows: int = LOCAL_EDGES):
    """nodes, first, nbr, sent to all tasks: the in-neighbours of nodes[i], by rank, are nbr[first[i]] up to nbr[first[i + 1]]."""
    if adj not in _sent:
        table = adj.select("node", "rk", "nbr").limit(most_rows + 1).toArrow()
        if table.num_rows > most_rows:
            raise ValueError(f"the adjacency has over {most_rows} edges: use stepwise or stitched")
        node, rk, nbr = (table.column(c).to_numpy() for c in ("node", "rk", "nbr"))
        order = np.lexsort((rk, node))
        nodes, first = np.unique(node[order], return_index=True)
        _sent[adj] = adj.sparkSession.sparkContext.broadcast((nodes, np.append(first, len(node)), nbr[order]))
    return _sent[adj]


def places(nodes: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where ``at`` are in the sorted ``nodes``, and whether they are there."""
    place = np.searchsorted(nodes, at)
    return place, (nodes[np.minimum(place, len(nodes) - 1)] == at if len(nodes) else np.zeros(len(at), bool))


def local(walkers: DataFrame, adj: DataFrame, longest: int, seed: int, most_rows: int = LOCAL_EDGES) -> DataFrame:
    """No exchange while walking: the adjacency, if it has at most ``most_rows`` edges, is sent to all,
    and the walks of a start are walked in one task; starts are dealt evenly before."""
    shared = to_tasks(adj, most_rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        nodes, first, nbr = shared.value
        for b in batches:
            start, number, planned = (np.asarray(b.column(c)).astype(np.int64) for c in ("start", "walk_no", "planned_len"))
            at, live, out = start.copy(), np.arange(len(start)), []
            for k in range(1, longest + 1):
                live = live[planned[live] >= k]
                place, there = places(nodes, at[live])
                live, place = live[there], place[there]
                if not len(live):
                    break
                bits = draws_local(seed, "step", start[live], number[live], k)
                at[live] = nbr[first[place] + bits % (first[place + 1] - first[place])]
                out.append((live, np.full(len(live), k), at[live]))
            if out:
                who, step, where = (np.concatenate(x) for x in zip(*out))
                yield pa.RecordBatch.from_arrays([pa.array(start[who]), pa.array(number[who], pa.int32()), pa.array(planned[who], pa.int32()), pa.array(step, pa.int32()), pa.array(where)], list(STEPS))

    tasks = 2 * adj.sparkSession.sparkContext.defaultParallelism
    return walkers.select("start", "walk_no", "planned_len").repartition(tasks, "start").mapInArrow(run, "start long, walk_no int, planned_len int, step int, node long")


def walker(strategy: str, adj: DataFrame):
    """``local`` if asked for and the adjacency is small enough, else ``stepwise``: the same steps."""
    return local if strategy == "local" and adj.count() <= LOCAL_EDGES else stepwise


def generate(g: Graph, plan: SamplingPlan, seed: int, strategy: str = "stepwise", layout: str = "merged", starts: DataFrame | None = None, adj: DataFrame | None = None, fast: bool = False) -> DataFrame:
    """Steps of the plan's walks. ``layout`` "per_length" walks each length on its own, as separate
    tasks in their slices of space; "merged" in one frontier. Both give the same rows. "local" goes
    stepwise, by the same draws, where the adjacency is too large to be sent to all."""
    adj = prepared(g) if adj is None else adj
    walkers = planned(g, plan, seed, starts)
    if strategy == "stitched":
        from .stitching import stitched

        return stitched(g, plan, walkers, adj, seed)[0]
    if strategy == "local" and fast:
        raise ValueError("fast draws are Spark's own: use stepwise")
    walk = walker(strategy, adj) if not fast else partial(stepwise, fast=True)
    if layout == "merged":
        return walk(walkers, adj, plan.longest, seed)
    out = None
    for n in range(1, plan.longest + 1):
        if plan.actual[n] or plan.rounding == "bernoulli":
            part = walk(walkers.filter(F.col("planned_len") == n), adj, n, seed)
            out = part if out is None else out.union(part)
    return out


def paths(steps: DataFrame) -> DataFrame:
    """start, walk_no, planned_len, path (nodes after the start, in order) of walks with steps."""
    grouped = steps.groupBy("start", "walk_no", "planned_len").agg(F.array_sort(F.collect_list(F.struct("step", "node"))).alias("s"))
    return grouped.select("start", "walk_no", "planned_len", F.col("s.node").alias("path"))


def decompose(walks: DataFrame) -> DataFrame:
    """(pair, step, node, walk_len, start) from walks (start, pair, planned_len, path): a row for each
    node after the start."""
    return walks.select("pair", F.posexplode("path").alias("p", "node"), F.col("planned_len").alias("walk_len"), "start").select("pair", (F.col("p") + 1).alias("step"), "node", "walk_len", "start")


def labels(walkers: DataFrame, seed: int, method: str = "pre_permuted") -> DataFrame:
    """start, walk_no, pair: the walks of each start in random order, pairs from 1. "window" ranks
    the walks, "pre_permuted" their numbers (no exchange where walkers come from ``planned``; same
    labels), "none" keeps the order of lengths: pairs of equal lengths, a biased control."""
    if method == "none":
        return walkers.select("start", "walk_no", F.col("walk_no").alias("pair"))
    if method == "window":
        order = Window.partitionBy("start").orderBy(draw(seed, "perm", F.col("start"), F.col("walk_no")), "walk_no")
        return walkers.select("start", "walk_no").withColumn("pair", F.row_number().over(order))
    raise ValueError(method)


def pre_permuted(g: Graph, plan: SamplingPlan, seed: int, starts: DataFrame | None = None) -> DataFrame:
    """``planned`` with pairs: the numbers of each start's walks are put in random order before
    anything is walked, within the start's row."""
    rows = _with_degree(g, starts).withColumn("lens", plan.lengths_of(F.col("start"), seed))
    keyed = F.transform(F.sequence(F.lit(1), F.size("lens")), lambda w: F.struct(draw(seed, "perm", F.col("start"), w).alias("h"), w.alias("w")))
    rows = rows.filter(F.size("lens") > 0).select("start", "deg", "lens", F.posexplode(F.array_sort(keyed)).alias("p", "x"))
    return rows.select("start", F.col("x.w").alias("walk_no"), (F.col("p") + 1).alias("pair"), F.element_at("lens", F.col("x.w")).alias("planned_len"), "deg")


def tuples(steps: DataFrame, pairs: DataFrame) -> DataFrame:
    """(pair, step, node, walk_len, start) of labelled walks."""
    return steps.join(pairs.select("start", "walk_no", "pair"), ["start", "walk_no"]).select("pair", "step", "node", F.col("planned_len").alias("walk_len"), "start")


def shortfall(steps_or_walks: DataFrame, plan: SamplingPlan) -> DataFrame:
    """len, missing: walks of each length that a sampler did not deliver (walks: start, walk_no,
    planned_len)."""
    got = steps_or_walks.select("start", "walk_no", "planned_len").distinct().groupBy(F.col("planned_len").alias("len")).agg(F.count(F.lit(1)).alias("got"))
    want = plan.frame(steps_or_walks.sparkSession).select("len", (F.col("actual") * F.lit(plan.n)).alias("want"))
    return want.join(got, "len", "left").select("len", (F.col("want") - F.coalesce("got", F.lit(0))).alias("missing"))
