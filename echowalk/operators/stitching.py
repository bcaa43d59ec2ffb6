"""Walks in a logarithmic number of rounds: segments of 2**k steps are joined to
segments of 2**k steps that start where they end, and walks of planned lengths are
put together from the binary digits of their lengths.

Each segment is used once. How many a node needs is estimated by a pilot of few
stepwise walks. Requests at a node are numbered in the order of hashes that do
not depend on the segments' contents; those beyond the supply are finished
stepwise from where they stand, with draws of their own.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce
from hashlib import md5
from weakref import WeakKeyDictionary

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.rng import draw, draws_of
from ..functions.sampling import SamplingPlan
from ..sources.graphs import Graph
from ..sources.tables import keep


TASK_STEPS = 500_000  # steps of walks a task of ``_stitched_local``, about
_SERVED = pa.schema([("a", pa.int64()), ("b", pa.int32()), ("c", pa.int32()), ("path", pa.list_(pa.int64())), ("at", pa.int64()), ("missing", pa.bool_())])
_piloted: WeakKeyDictionary[DataFrame, dict] = WeakKeyDictionary()


@dataclass(frozen=True)
class Supply:
    """``pilot`` walks of each node estimate visits; ``slack`` multiplies the estimates and
    ``floor`` * ln n is added where a node is visited at all. ``reuse``: a segment serves any number
    of requests (walks are then correlated; an ablation)."""

    pilot: int = 8
    slack: float = 1.3
    floor: float = 3.0
    reuse: bool = False


def _pilot(g: Graph, adj: DataFrame, longest: int, pilot: int, seed: int) -> DataFrame:
    """start, offset, node, n: where pilot walks of the full length are after each number of steps. Written
    once an adjacency."""
    from . import walks

    made = _piloted.setdefault(adj, {})
    if (longest, pilot, seed) in made:
        return made[longest, pilot, seed]
    d = walks._with_degree(g, None)
    walkers = d.select("start", "deg", F.explode(F.sequence(F.lit(1), F.lit(pilot))).alias("walk_no")).withColumn("planned_len", F.lit(longest))
    steps = walks.walker("local", adj)(walkers, adj, longest, seed + 7919)
    zero = d.select("start", F.lit(0).alias("offset"), F.col("start").alias("node"), F.lit(pilot).cast("long").alias("n"))
    made[longest, pilot, seed] = keep(steps.groupBy("start", F.col("step").alias("offset"), "node").agg(F.count(F.lit(1)).alias("n")).union(zero), "pilot")
    return made[longest, pilot, seed]


def _to_all(g: Graph):
    """``F.broadcast`` for a table of rows of nodes, if there are few enough."""
    from . import walks

    return F.broadcast if g.size() <= walks.LOCAL_EDGES else lambda df: df


def supplies(g: Graph, plan: SamplingPlan, pilot: DataFrame, levels: int, rule: Supply, starts: DataFrame) -> dict[int, DataFrame]:
    """For each level: node, use (segments for walks of ``starts``), heads, tails (estimates, rounded up)."""
    extra = math.ceil(rule.floor * math.log(max(2, plan.n)))
    up = lambda x: F.ceil(x * rule.slack).cast("int") + F.when(x > 0, extra).otherwise(0)
    small = _to_all(g)
    nodes = g.nodes.select(F.col("id").alias("node"))
    uses = []
    for k in range(levels + 1):
        weight = F.lit(0.0)
        for offset, count in ((n >> (k + 1) << (k + 1), count) for n, count in enumerate(plan.actual) if n >> k & 1):
            weight = weight + F.when(F.col("offset") == offset, F.lit(float(count))).otherwise(0.0)
        uses.append((F.sum(F.col("n") * weight) / rule.pilot).alias(f"use{k}"))
    # of all levels at once: the pilot is the largest table here
    use = keep(nodes.join(pilot.join(small(starts), "start", "left_semi").groupBy("node").agg(*uses), "node", "left"), "uses")
    heads = nodes.withColumn("heads", F.lit(0))
    out: dict[int, DataFrame] = {}
    for k in range(levels, -1, -1):
        arrive = pilot.filter(F.col("offset") == (1 << k)).join(small(heads.select(F.col("node").alias("start"), "heads")), "start").groupBy("node").agg((F.sum(F.col("n") * F.col("heads")) / rule.pilot).alias("tails"))
        row = use.select("node", F.col(f"use{k}").alias("use")).join(small(heads), "node", "left").join(small(arrive), "node", "left")
        row = row.select("node", up(F.coalesce("use", F.lit(0.0))).alias("use"), F.coalesce("heads", F.lit(0)).alias("heads"), up(F.coalesce("tails", F.lit(0.0))).alias("tails"))
        out[k] = keep(row, "supply")
        heads = out[k].select("node", (F.col("use") + F.col("heads") + F.col("tails")).alias("heads"))
    return out


def _serve(requests: DataFrame, segments: DataFrame, available: DataFrame, seed: int, purpose: str, reuse: bool) -> tuple[DataFrame, DataFrame]:
    """Requests (rid, at, ...) with the path of a segment that starts at ``at``, and those that get
    none. ``segments``: node, no (from 1), path, end; ``available``: node, n."""
    key = draw(seed, purpose, F.col("rid"))
    if reuse:
        numbered = requests.join(available.select(F.col("node").alias("at"), "n"), "at", "left").withColumn("no", F.when(F.col("n") > 0, F.pmod(key, F.col("n")) + 1)).drop("n")
    else:
        numbered = requests.withColumn("no", F.row_number().over(Window.partitionBy("at").orderBy(key, "rid")))
    got = keep(numbered.join(segments.select(F.col("node").alias("at"), "no", F.col("path").alias("more"), F.col("end").alias("to")), ["at", "no"], "left").drop("no"), "served")
    return got.filter("more is not null"), got.filter("more is null").drop("more", "to")


def stitched(g: Graph, plan: SamplingPlan, walkers: DataFrame, adj: DataFrame, seed: int, rule: Supply = Supply()) -> tuple[DataFrame, DataFrame]:
    """Steps of the walkers' walks, and (level, missing): requests that found no segment."""
    from . import walks

    levels = max(0, int(math.log2(max(1, plan.longest))))
    pilot = _pilot(g, adj, plan.longest, rule.pilot, seed)
    supply = supplies(g, plan, pilot, levels, rule, walkers.select("start").distinct())
    if max(adj.count(), g.size()) <= walks.LOCAL_EDGES:
        return _stitched_local(g, plan, walkers, adj, seed, rule, supply, levels)
    degree = keep(walks._with_degree(g, None).select(F.col("start").alias("node"), "deg"), "degree")
    edges = walks.to_all(adj).select("node", "rk", "nbr")
    short: list[tuple[int, int]] = []

    base = supply[0].select("node", (F.col("use") + F.col("heads") + F.col("tails")).alias("all")).filter(F.col("all") > 0).join(degree, "node")
    base = base.select("node", "deg", F.explode(F.sequence(F.lit(1), F.col("all"))).alias("no"))
    base = base.withColumn("rk", F.when(F.col("deg") > 0, (draw(seed, "segment", F.col("node"), F.col("no")) % F.col("deg")).cast("int")))
    level0 = base.join(edges, ["node", "rk"], "left").select("node", "no", F.when(F.col("nbr").isNull(), F.array().cast("array<long>")).otherwise(F.array("nbr")).alias("path"), F.col("nbr").alias("end"))
    segments = {0: keep(level0, "segments")}
    for k in range(levels):
        # numbers: 1..heads head a longer segment, then tails, then what walks use
        shares = supply[k]
        owned = segments[k].join(shares, "node")
        heads = owned.filter("no <= heads").select(F.concat_ws("/", "node", "no").alias("rid"), F.col("node").alias("origin"), "no", "path", F.col("end").alias("at"))
        whole = heads.filter("at is null").select(F.col("origin").alias("node"), "no", "path", F.col("at").alias("end"))
        tails = owned.filter("no > heads and no <= heads + tails").select("node", (F.col("no") - F.col("heads")).alias("no"), "path", "end")
        served, unmet = _serve(heads.filter("at is not null").withColumnRenamed("no", "own_no"), tails, shares.select("node", F.col("tails").alias("n")), seed, f"tail{k}", rule.reuse)
        missing = unmet.count()
        short.append((k, missing))
        joined = served.select(F.col("origin").alias("node"), F.col("own_no").alias("no"), F.concat("path", "more").alias("path"), F.col("to").alias("end"))
        if missing:
            joined = joined.union(_walk_on(unmet, adj, degree, 1 << k, seed, f"fix{k}").select(F.col("origin").alias("node"), F.col("own_no").alias("no"), "path", F.col("at").alias("end")))
        segments[k + 1] = keep(joined.union(whole), "segments")
    going = walkers.select(F.concat_ws("/", "start", "walk_no").alias("rid"), "start", "walk_no", "planned_len", F.array().cast("array<long>").alias("path"), F.col("start").alias("at"))
    for k in range(levels, -1, -1):
        asks = F.col("planned_len").bitwiseAND(F.lit(1 << k)) != 0
        waiting, resting = going.filter(asks & F.col("at").isNotNull()), going.filter(~asks | F.col("at").isNull())
        owned = segments[k].join(supply[k], "node")
        free = owned.filter("no > heads + tails").select("node", (F.col("no") - F.col("heads") - F.col("tails")).alias("no"), "path", "end")
        if k == levels:
            free = segments[k].select("node", "no", "path", "end")
        served, unmet = _serve(waiting, free, supply[k].select("node", F.col("use").alias("n")), seed, f"use{k}", rule.reuse)
        missing = unmet.count()
        short.append((k, missing))
        moved = served.select("rid", "start", "walk_no", "planned_len", F.concat("path", "more").alias("path"), F.col("to").alias("at"))
        if missing:
            moved = moved.union(_walk_on(unmet, adj, degree, 1 << k, seed, f"last{k}").select("rid", "start", "walk_no", "planned_len", "path", "at"))
        going = keep(moved.union(resting), "stitched")
    steps = going.select("start", "walk_no", "planned_len", F.posexplode("path").alias("p", "node")).select("start", "walk_no", "planned_len", (F.col("p") + 1).alias("step"), "node")
    return steps, g.edges.sparkSession.createDataFrame(short or [(0, 0)], "level int, missing long").groupBy("level").agg(F.sum("missing").alias("missing"))


def _stitched_local(g: Graph, plan: SamplingPlan, walkers: DataFrame, adj: DataFrame, seed: int, rule: Supply, supply: dict[int, DataFrame], levels: int) -> tuple[DataFrame, DataFrame]:
    """``stitched`` by the same draws where the adjacency is sent to all: requests and segments come to
    the task of their node in one exchange a level. Segments of one step are functions of their numbers
    and made where they are needed."""
    from . import walks

    shared, none = walks.to_tasks(adj), F.array().cast("array<long>")
    tasks = max(2 * adj.sparkSession.sparkContext.defaultParallelism, -(-g.size() * plan.steps // TASK_STEPS))

    def serve(requests: DataFrame, segments: DataFrame, k: int, purpose: str, finish: str) -> DataFrame:
        """a, b, c, path, at, missing. ``requests``: a, b, c, path, at (null: returned as they are); ``segments``: key, b
        (numbers from 1), path, at, at level 0 a row for each node: b (how many), at (numbers before them)."""
        asks = requests.select(F.coalesce("at", "a").alias("key"), "a", "b", "c", "path", "at", F.lit(True).alias("asks"))
        has = segments.select("key", F.lit(0).cast("long").alias("a"), "b", F.lit(0).alias("c"), "path", "at", F.lit(False).alias("asks"))
        run = _server(shared, seed, k, purpose, finish, rule.reuse)
        return keep(asks.union(has).repartition(tasks, "key").mapInArrow(run, "a long, b int, c int, path array<long>, at long, missing boolean"), "served")

    def numbered(k: int, before: Column, many: Column) -> DataFrame:
        """``segments`` of a level: ``many`` numbers from ``before`` + 1 on."""
        if k == 0:
            return supply[0].filter(many > 0).select(F.col("node").alias("key"), many.alias("b"), none.alias("path"), before.cast("long").alias("at"))
        no = (F.col("no") - before).alias("b")
        return segments[k].join(F.broadcast(supply[k]), "node").filter((F.col("no") > before) & (F.col("no") <= before + many)).select(F.col("node").alias("key"), no, "path", "at")

    segments, short = {}, []
    first = supply[0].filter("heads > 0").repartition(tasks, "node").select("node", F.explode(F.sequence(F.lit(1), F.col("heads"))).alias("no"))
    for k in range(levels):
        if k == 0:
            owned = first.mapInArrow(_first_steps(shared, seed), "node long, no int, path array<long>, at long")
        else:
            owned = segments[k].join(F.broadcast(supply[k].select("node", "heads")), "node").filter("no <= heads")
        heads = owned.select(F.col("node").alias("a"), F.col("no").alias("b"), F.lit(0).alias("c"), "path", "at")
        got = serve(heads, numbered(k, F.col("heads"), F.col("tails")), k, f"tail{k}", f"fix{k}")
        short.append(got.filter("missing").select(F.lit(k).alias("level")))
        segments[k + 1] = got.select(F.col("a").alias("node"), F.col("b").alias("no"), "path", "at")
    walkers = keep(walkers.filter("planned_len > 0").select("start", "walk_no", "planned_len"), "walkers")
    going = [walkers.select(F.col("start").alias("a"), F.col("walk_no").alias("b"), F.col("planned_len").alias("c"), none.alias("path"), F.col("start").alias("at"))]
    for k in range(levels, -1, -1):
        asks = (F.col("c").bitwiseAND(F.lit(1 << k)) != 0) & F.col("at").isNotNull()
        waiting = reduce(DataFrame.union, (x.filter(asks) for x in going))
        got = serve(waiting, numbered(k, F.col("heads") + F.col("tails"), F.col("use")), k, f"use{k}", f"last{k}")
        short.append(got.filter("missing").select(F.lit(k).alias("level")))
        going = [*(x.filter(~asks) for x in going), got.drop("missing")]
    done = reduce(DataFrame.union, going)
    steps = done.select(F.col("a").alias("start"), F.col("b").alias("walk_no"), F.col("c").alias("planned_len"), F.posexplode("path").alias("p", "node"))
    every = adj.sparkSession.range(levels + 1).select(F.col("id").cast("int").alias("level"))
    missing = every.join(reduce(DataFrame.union, short).groupBy("level").agg(F.count(F.lit(1)).alias("missing")), "level", "left")
    return steps.select("start", "walk_no", "planned_len", (F.col("p") + 1).alias("step"), "node"), missing.select("level", F.coalesce("missing", F.lit(0)).alias("missing"))


def _one_step(sent: tuple, seed: int, node: np.ndarray, no: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where segments of one step end, and whether they have a step."""
    from .walks import places

    nodes, first, nbr = sent
    place, there = places(nodes, node)
    to, place = np.zeros(len(node), np.int64), place[there]
    bits = draws_of(f"{seed}|segment|%d|%d", node[there], no[there])
    to[there] = nbr[first[place] + bits % (first[place + 1] - first[place])]
    return to, there


def _first_steps(shared, seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            to, there = _one_step(shared.value, seed, np.asarray(b.column("node")), np.asarray(b.column("no")))
            path = pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(there)), pa.int32()), pa.array(to[there]))
            yield pa.RecordBatch.from_arrays([b.column("node"), b.column("no"), path, pa.array(to, mask=~there)], ["node", "no", "path", "at"])

    return run


def _lists(values: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """(lengths, values) of lists that are put together row by row from several (lengths, values)."""
    many = np.stack([n for n, _ in values], axis=1)
    place = np.zeros(many.size + 1, np.int64)
    np.cumsum(many.ravel(), out=place[1:])
    out = np.zeros(place[-1], np.int64)
    for k, (n, v) in enumerate(values):
        begin = place[:-1].reshape(many.shape)[:, k]
        out[np.arange(len(v)) + np.repeat(begin - (np.cumsum(n) - n), n)] = v
    return many.sum(axis=1), out


def _server(shared, seed: int, k: int, purpose: str, finish: str, reuse: bool):
    """Gives each request of a task's nodes a segment that starts there, in the order of the requests' hashes; those
    left over take 2**k steps of their own."""
    from .walks import places

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        batches = list(batches)
        if not batches:
            return
        every = pa.Table.from_batches(batches)
        ended = every.filter(pc.and_(every["asks"], pc.is_null(every["at"])))
        if ended.num_rows:
            yield from ended.select(["a", "b", "c", "path", "at"]).append_column("missing", pa.repeat(False, ended.num_rows)).cast(_SERVED).to_batches(max_chunksize=65_536)
        asks = every.filter(pc.and_(every["asks"], pc.is_valid(every["at"]))).combine_chunks()
        has = every.filter(pc.invert(every["asks"])).combine_chunks()
        del every, batches
        at, a, b = (asks[c].to_numpy() for c in ("key", "a", "b"))
        n = len(at)
        if not n:
            return
        bits = draws_of(f"{seed}|{purpose}|%d/%d", a, b)
        node, no = has["key"].to_numpy(), has["b"].to_numpy()
        order = np.lexsort((no, node))
        own, begin, many = np.unique(node[order], return_index=True, return_counts=True)
        if k == 0:
            many = no[order].astype(np.int64)
        place, there = places(own, at)
        place = np.where(there, place, 0)
        free = np.where(there, many[place], 0) if len(own) else np.zeros(n, np.int64)
        if reuse:
            nth = bits % np.maximum(free, 1)
        else:
            by = np.lexsort((bits, at))
            same = np.flatnonzero((np.diff(at[by]) == 0) & (np.diff(bits[by]) == 0))
            for begins in same[np.append(True, np.diff(same) > 1)] if len(same) else ():
                ends = begins + 1
                while ends < n and at[by[ends]] == at[by[begins]] and bits[by[ends]] == bits[by[begins]]:
                    ends += 1
                by[begins:ends] = sorted(by[begins:ends], key=lambda i: f"{a[i]}/{b[i]}")
            ranked = at[by]
            new = np.append(True, ranked[1:] != ranked[:-1])
            nth = np.empty(n, np.int64)
            nth[by] = np.arange(n) - np.flatnonzero(new)[np.cumsum(new) - 1]
        met = nth < free
        to, going = at.copy(), np.ones(n, bool)
        got, unmet = np.flatnonzero(met), np.flatnonzero(~met)
        if k:
            taken = pa.array(order[begin[place[got]] + nth[got]])
            paths, ends = has["path"].combine_chunks().take(taken), has["at"].combine_chunks().take(taken)
            lengths, values = np.asarray(paths.value_lengths()).astype(np.int64), np.asarray(paths.flatten())
            going[got], to[got] = np.asarray(ends.is_valid()), np.asarray(ends.fill_null(0))
        else:
            before = has["at"].to_numpy()[order[place[got]]]
            to[got], going[got] = _one_step(shared.value, seed, at[got], before + nth[got] + 1)
            lengths, values = going[got].astype(np.int64), to[got][going[got]]
        more = np.zeros(n, np.int64)
        more[got] = lengths
        own_steps = np.zeros(n, np.int64)
        if len(unmet):
            made, own_steps[unmet], to[unmet], going[unmet] = _own_steps(shared.value, at[unmet], [f"{seed}|{finish}|{x}/{y}|".encode() for x, y in zip(a[unmet].tolist(), b[unmet].tolist())], 1 << k)
        else:
            made = np.zeros(0, np.int64)
        path = asks["path"].combine_chunks()
        parts = [(np.asarray(path.value_lengths()).astype(np.int64), np.asarray(path.flatten())), (more, values), (own_steps, made)]
        lengths, values = _lists(parts)
        path = pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(lengths)).astype(np.int32)), pa.array(values))
        out = pa.table({"a": asks["a"], "b": asks["b"], "c": asks["c"], "path": path, "at": pa.array(to, mask=~going), "missing": pa.array(~met)})
        yield from out.cast(_SERVED).to_batches(max_chunksize=65_536)

    return run


def _own_steps(sent: tuple, start: np.ndarray, keys: list[bytes], steps: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The steps made from ``start`` on, row after row, how many each made, where it stands, and whether it was not stopped."""
    from .walks import places

    nodes, first, nbr = sent
    n, at, live = len(start), start.copy(), np.arange(len(start))
    made, many, going = np.zeros((n, steps), np.int64), np.zeros(n, np.int64), np.ones(n, bool)
    for k in range(steps):
        place, there = places(nodes, at[live])
        going[live[~there]] = False
        live, place = live[there], place[there]
        if not len(live):
            break
        end = b"%d" % k
        bits = np.frombuffer(b"".join([md5(keys[i] + end).digest() for i in live.tolist()]), ">u4")[::4].astype(np.int64)
        at[live] = made[live, k] = nbr[first[place] + bits % (first[place + 1] - first[place])]
        many[live] += 1
    return made[np.arange(steps) < many[:, None]], many, at, going


def _walk_on(unmet: DataFrame, adj: DataFrame, degree: DataFrame, steps: int, seed: int, purpose: str) -> DataFrame:
    """Adds ``steps`` steps to the paths of the unmet, from where they stand."""
    from . import walks

    if adj.count() <= walks.LOCAL_EDGES:
        return _walk_on_local(unmet, walks.to_tasks(adj), steps, seed, purpose)
    now, edges = unmet, walks.to_all(adj).select(F.col("node").alias("at"), "rk", "nbr")
    for k in range(steps):
        # a walk at a dead end has no ``at`` and stays as it is
        at = now.join(degree.withColumnRenamed("node", "at"), "at", "left").withColumn("rk", F.when(F.col("deg") > 0, (draw(seed, purpose, F.col("rid"), F.lit(k)) % F.col("deg")).cast("int")))
        moved = at.join(edges, ["at", "rk"], "left")
        path = F.when(F.col("nbr").isNull(), F.col("path")).otherwise(F.concat("path", F.array("nbr")))
        now = keep(moved.withColumns({"path": path}).drop("at", "rk", "deg").withColumnRenamed("nbr", "at").select(*unmet.columns), "finishing")
    return now


def _walk_on_local(unmet: DataFrame, shared, steps: int, seed: int, purpose: str) -> DataFrame:
    """``_walk_on`` by the same draws without an exchange, where the adjacency is sent to all."""
    columns = unmet.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            path, live = b.column("path"), np.flatnonzero(np.asarray(b.column("at").is_valid()))
            rids = b.column("rid").take(pa.array(live)).to_pylist()
            at, stopped, many = np.asarray(b.column("at").fill_null(0)).copy(), np.ones(b.num_rows, bool), np.zeros(b.num_rows, np.int64)
            made, many[live], at[live], going = _own_steps(shared.value, at[live], [f"{seed}|{purpose}|{r}|".encode() for r in rids], steps)
            stopped[live] = ~going
            lengths, values = _lists([(np.asarray(path.value_lengths()).astype(np.int64), np.asarray(path.flatten())), (many, made)])
            longer = pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(lengths)).astype(np.int32)), pa.array(values))
            new = {"path": longer, "at": pa.array(at, mask=stopped)}
            yield pa.RecordBatch.from_arrays([new.get(c, b.column(c)) for c in columns], columns)

    return unmet.mapInArrow(run, unmet.schema)
