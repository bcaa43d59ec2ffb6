"""Exact similarities by iteration, and what the estimators expect."""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce
from weakref import WeakKeyDictionary

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.sampling import SamplingPlan
from ..sources.graphs import Graph
from ..sources.tables import keep


def _in(g: Graph, node: str, nbr: str, deg: str) -> DataFrame:
    d = g.edges.groupBy(F.col("dst").alias(node)).agg(F.count(F.lit(1)).alias(deg))
    return g.edges.select(F.col("dst").alias(node), F.col("src").alias(nbr)).join(d, node)


def _iterate(scores: DataFrame, left: DataFrame, right: DataFrame, c: float) -> DataFrame:
    """One application of the recursion to scores(a, b, score) with a diagonal of ones. Similarities
    are symmetric, so pairs are kept both ways."""
    half = scores.join(left, F.col("a") == F.col("x")).groupBy("u", "b").agg((F.sum(F.col("score") / F.col("du"))).alias("h"))
    whole = half.join(right, F.col("b") == F.col("y")).groupBy("u", "v").agg((F.sum(F.col("h") / F.col("dv")) * c).alias("score"))
    return whole.filter("u != v").select(F.col("u").alias("a"), F.col("v").alias("b"), "score")


def iterates(g: Graph, c: float, iterations: int):
    """Off-diagonal scores (a, b, score) after 1, 2, ... applications."""
    left, right = keep(_in(g, "u", "x", "du"), "in"), keep(_in(g, "v", "y", "dv"), "in")
    ones = g.nodes.select(F.col("id").alias("a"), F.col("id").alias("b"), F.lit(1.0).alias("score"))
    off = ones.filter(F.lit(False))
    for _ in range(iterations):
        off = keep(_iterate(ones.union(off), left, right, c), "scores")
        yield off


def all_pairs(g: Graph, c: float = 0.6, iterations: int = 10, tol: float | None = None) -> DataFrame:
    """a, b, score for all pairs above zero, the diagonal included; off by c**(iterations + 1) at
    most. ``tol``: stop when no score moves more."""
    before = off = None
    for off in iterates(g, c, iterations):
        if tol is not None and before is not None:
            moved = off.join(before.withColumnRenamed("score", "old"), ["a", "b"], "full").agg(F.max(F.abs(F.coalesce("score", F.lit(0.0)) - F.coalesce("old", F.lit(0.0))))).first()[0]
            if (moved or 0.0) <= tol:
                break
        before = off
    ones = g.nodes.select(F.col("id").alias("a"), F.col("id").alias("b"), F.lit(1.0).alias("score"))
    return ones if off is None else ones.union(off)


SMALL_SIDE = 1024  # nodes whose pairs one machine holds
_sided: WeakKeyDictionary[DataFrame, tuple[tuple, dict]] = WeakKeyDictionary()


def _sides(g: Graph, adj: DataFrame, source: int, iterations: int) -> dict:
    """What the source's scores need whatever c is: seen (id, odd), the sizes of its sides, and whether they are two.
    Kept for an adjacency's last source."""
    from .walks import reach

    if adj not in _sided or _sided[adj][0] != (source, iterations):
        seen = keep(reach(g, g.nodes.filter(F.col("id") == source).select("id"), iterations, adj), "sides")
        sizes = {r["odd"]: r["count"] for r in seen.groupBy("odd").count().collect()}
        two = seen.groupBy("id").count().filter("count > 1").isEmpty()
        _sided[adj] = (source, iterations), {"seen": seen, "sizes": sizes, "two": two}
    return _sided[adj][1]


def single_source(g: Graph, source: int, c: float = 0.6, iterations: int = 10) -> DataFrame:
    """source, node, score: one row of ``all_pairs``. Where the source's nodes have two sides, pairs being
    of one side only, and one side is small, pairs of the other side are never made. Else only rows of
    the source's ancestors are made (``_ancestor_rows``), where the graph is small enough for that."""
    from .walks import prepared

    adj = prepared(g)
    known = _sides(g, adj, source, iterations)
    seen, sizes = known["seen"], known["sizes"]
    if not (known["two"] and sizes and iterations and min(sizes.get(0, 0), sizes.get(1, 0)) <= SMALL_SIDE):
        if not iterations:
            return all_pairs(g, c, 0).filter(F.col("a") == source).select(F.col("a").alias("source"), F.col("b").alias("node"), "score")
        rows = _ancestor_rows(adj, source, c, iterations) if adj.count() <= MOST_EDGES else None
        return _from_diagonals(adj, source, c, iterations) if rows is None else rows
    small = 0 if sizes.get(0, 0) <= sizes.get(1, 0) else 1
    ids = np.array(sorted(r["id"] for r in seen.filter(F.col("odd") == small).select("id").collect()), np.int64)
    s = _side_matrix(adj, seen.filter(F.col("odd") == 1 - small).select("id"), ids, c, iterations - small, known)
    spark, schema = g.edges.sparkSession, "source long, node long, score double"
    at = {v: k for k, v in enumerate(ids.tolist())}
    if small == 0:
        return spark.createDataFrame([(source, v, float(s[at[source], k])) for v, k in at.items() if s[at[source], k] > 0], schema)
    mine = [r["nbr"] for r in adj.filter(F.col("node") == source).select("nbr").collect()]
    push = sum((s[at[x]] for x in mine), np.zeros(len(ids))) / max(1, len(mine))
    pushed = spark.createDataFrame([(v, float(push[k])) for v, k in at.items()], "nbr long, h double")
    rest = adj.filter(F.col("node") != source).join(F.broadcast(pushed), "nbr").groupBy("node").agg((F.sum(F.col("h") / F.col("node_deg")) * c).alias("score")).filter("score > 0")
    return rest.select(F.lit(source).cast("long").alias("source"), "node", "score").union(spark.createDataFrame([(source, source, 1.0)], schema))


def _middle(adj: DataFrame, others: DataFrame, ids: np.ndarray) -> DataFrame:
    """For each node of the other side: places in ``ids`` and degrees of the nodes that it leads to and that lead to it."""
    side = adj.sparkSession.createDataFrame([(v, k) for k, v in enumerate(ids.tolist())], "id long, k int")
    out_of = adj.join(F.broadcast(side.select(F.col("id").alias("node"), "k")), "node").groupBy(F.col("nbr").alias("y")).agg(F.collect_list(F.struct("k", F.col("node_deg").alias("d"))).alias("outs"))
    into = adj.join(F.broadcast(side.select(F.col("id").alias("nbr"), "k")), "nbr").groupBy(F.col("node").alias("y")).agg(F.collect_list(F.struct("k", F.col("node_deg").alias("d"))).alias("ins"))
    rows = out_of.join(others.select(F.col("id").alias("y")), "y", "left_semi").join(into, "y", "left")
    return keep(rows.select(*(F.transform(x, lambda e: e[f]).alias(f"{x}_{f}") for x in ("outs", "ins") for f in ("k", "d"))), "middle")


def _side_matrix(adj: DataFrame, others: DataFrame, ids: np.ndarray, c: float, iterations: int, known: dict) -> np.ndarray:
    """Scores among ``ids`` (one side, sorted) after ``iterations``, two at a time. With B(u, a) the chance
    of two steps from u to a over the other side and w(y) the chance that two walks which meet at y
    have not met a step on, S becomes c**2 B S B' + c sum over y of p(u, y) p(v, y) w(y), for u != v. ``known``
    keeps what does not depend on c."""
    spark, n = adj.sparkSession, len(ids)
    if "rows" not in known:
        known["rows"] = _middle(adj, others, ids)
    rows = known["rows"]

    def dense(batch: pa.RecordBatch, side: str) -> np.ndarray:
        k, d = (batch.column(f"{side}_{f}") for f in "kd")
        who = np.repeat(np.arange(len(k)), np.nan_to_num(np.asarray(k.value_lengths().fill_null(0))).astype(np.int64))
        out = np.zeros((len(k), n))
        out[who, np.asarray(k.flatten())] = 1.0 / np.asarray(d.flatten())
        return out

    def summed(total) -> np.ndarray:
        """The sum over all batches of ``total``(outs, ins), matrices of a batch's rows by ids."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            t = np.zeros((n, n))
            for b in batches:
                for at in range(0, b.num_rows, 2048):
                    part = b.slice(at, 2048)
                    t += total(dense(part, "outs"), dense(part, "ins"))
            u = np.flatnonzero(t.any(1))
            yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(list(t[u]), pa.list_(pa.float64()))], ["u", "t"])

        out = np.zeros((n, n))
        for r in rows.mapInArrow(run, "u long, t array<double>").toLocalIterator():
            out[r["u"]] += r["t"]
        return out

    s = np.eye(n)
    if iterations > 1 and "steps" not in known:
        known["steps"] = summed(lambda p, q: p.T @ q)
    two = known.get("steps")
    if iterations % 2:
        if "met" not in known:
            known["met"] = summed(lambda p, q: p.T @ p)
        s = c * known["met"]
        np.fill_diagonal(s, 1.0)
    for _ in range(iterations // 2):
        held = spark.sparkContext.broadcast(s)
        s = c * c * two @ s @ two.T + c * summed(lambda p, q: p.T @ (p * (1.0 - c * ((q @ held.value) * q).sum(1))[:, None]))  # noqa: B023
        np.fill_diagonal(s, 1.0)
    return s


MOST_EDGES = 2_000_000  # of a graph that the driver and all tasks hold
MOST_CELLS = 1 << 25  # scores that one iteration may ship; each is written
CELLS = 1 << 21  # scores that a task holds
TASK_EDGES = 8_000_000  # of ancestors, that all tasks hold


class _Means:
    """Rows of in-neighbours of nodes 0..n-1, and means of a matrix's rows over them."""

    def __init__(self, first: np.ndarray, nbr: np.ndarray):
        self.first, self.nbr = first, nbr

    def around(self, of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """In-neighbours of each of the nodes ``of``, one after another, and how many each has."""
        size = self.first[of + 1] - self.first[of]
        at = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
        return self.nbr[np.repeat(self.first[of], size) + at], size

    def over(self, x: np.ndarray, rows: np.ndarray, of: np.ndarray) -> np.ndarray:
        """The mean of ``x``, whose rows are those of the sorted nodes ``rows``, over in-neighbours of each node."""
        out, few = np.zeros((len(of), x.shape[1])), max(1, (CELLS >> 1) // max(1, x.shape[1]))
        done = np.cumsum(self.first[of + 1] - self.first[of])
        at = 0
        while at < len(of):
            to = max(at + 1, int(np.searchsorted(done, (done[at - 1] if at else 0) + few, "right")))
            nbr, size = self.around(of[at:to])
            have = np.flatnonzero(size)
            if len(have):
                begins = (np.cumsum(size) - size)[have]
                out[at + have] = np.add.reduceat(x[np.searchsorted(rows, nbr)], begins, axis=0) / size[have, None]
            at = to
        return out

    def ahead(self, i: np.ndarray, at: np.ndarray, m: np.ndarray, many: int, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Chances ``m`` that walk i of ``many`` is at ``at``, one step on; sorted by walks and nodes."""
        done = np.cumsum(self.first[at + 1] - self.first[at])
        total = int(done[-1]) if len(done) else 0
        dense, low = np.zeros(many * n) if 8 * total >= many * n else None, 0
        keys, values = np.zeros(0, np.int64), np.zeros(0)
        while low < len(at):
            high = len(at) if dense is None else max(low + 1, int(np.searchsorted(done, (done[low - 1] if low else 0) + CELLS, "right")))
            nbr, size = self.around(at[low:high])
            keys, values = np.repeat(i[low:high] * n, size) + nbr, np.repeat(m[low:high] / np.maximum(size, 1), size)
            if dense is not None:
                dense += np.bincount(keys, values, many * n)
            low = high
        if dense is not None:
            found = np.flatnonzero(dense)
            return found // n, found % n, dense[found]
        order = np.argsort(keys)
        keys, values = keys[order], values[order]
        new = np.flatnonzero(np.append(True, keys[1:] != keys[:-1])) if len(keys) else keys
        return keys[new] // n, keys[new] % n, np.add.reduceat(values, new) if len(keys) else values


def _ancestor_rows(adj: DataFrame, source: int, c: float, iterations: int) -> DataFrame | None:
    """source, node, score. The source's row after k iterations needs only rows of its in-neighbours after
    k - 1, and so on. With P the chances of steps, S becomes c P S P' with a diagonal of ones: a task has
    whole rows and steps on their columns, or whole columns and steps on their rows, twice each, so
    an iteration ships its rows once. None if a set of ancestors has too many rows for that."""
    spark, schema = adj.sparkSession, "source long, node long, score double"
    table = adj.select("node", "nbr").toArrow()
    node, nbr = (table.column(k).to_numpy() for k in ("node", "nbr"))
    ids = np.unique(np.concatenate([node, nbr, np.array([source], np.int64)]))
    n, order = len(ids), np.lexsort((nbr, node))
    first = np.zeros(n + 1, np.int64)
    first[1:] = np.cumsum(np.bincount(np.searchsorted(ids, node), minlength=n))
    means, every = _Means(first, np.searchsorted(ids, nbr[order])), np.arange(n)
    rows = [np.searchsorted(ids, np.array([source], np.int64))]  # by steps back from the source
    for _ in range(iterations - 1):
        rows.append(np.unique(means.around(rows[-1])[0]))
        if len(rows[-1]) * n > MOST_CELLS:
            return None
    if not len(rows[-1]):  # walks of the source end before
        last = next(t for t, r in enumerate(rows) if not len(r))
        rows, iterations = rows[:last], last
    tasks = 2 * spark.sparkContext.defaultParallelism

    def blocks(size: int, other: int) -> np.ndarray:
        """Borders of blocks of ``size`` rows or columns of length ``other``."""
        count = min(size, max(1, -(-size * other // CELLS), tasks if size * other > CELLS // 8 else 1))
        return np.linspace(0, size, count + 1).astype(np.int64)

    # borders[k]: of what tasks of iteration k hold whole, rows of rows[iterations - k] or (k even) columns
    borders = {k: blocks(len(rows[iterations - k]), n) if k % 2 else blocks(n, len(rows[iterations - k + 1])) for k in range(1, iterations + 1)}
    shared = spark.sparkContext.broadcast((means, rows, borders))

    def one(k: int, own: int, x: np.ndarray) -> pa.RecordBatch:
        means, rows, borders = shared.value
        low, high = borders[k][own : own + 2]
        mine = rows[iterations - k][low:high] if k % 2 else every[low:high]
        axis, of = (every, every) if k % 2 else (rows[iterations - k + 1], rows[iterations - k])
        s = c * means.over(x, axis, of)
        own_row, own_col = np.searchsorted(of, mine), np.arange(len(mine))
        there = own_row < len(of)
        there[there] = of[own_row[there]] == mine[there]
        s[own_row[there], own_col[there]] = 1.0
        if k == iterations:
            found = s[:, 0] if k % 2 else s[0]
            at = np.flatnonzero(found > 0)
            return pa.RecordBatch.from_arrays([pa.array(np.zeros(len(at), np.int32)), pa.array((at if k % 2 else at + low).astype(np.int32)), pa.array([x.tobytes() for x in found[at]], pa.binary())], ["to", "sent", "part"])
        z = means.over(s, of, every if k % 2 else rows[iterations - k - 1])
        to = borders[k + 1]
        parts = [np.ascontiguousarray(z[a:b].T).tobytes() for a, b in zip(to, to[1:])]
        return pa.RecordBatch.from_arrays([pa.array(np.arange(len(parts), dtype=np.int32)), pa.array(np.full(len(parts), own, np.int32)), pa.array(parts, pa.binary())], ["to", "sent", "part"])

    def begin(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        means, rows, borders = shared.value
        for own in (b for batch in batches for b in batch.column("id").to_pylist()):
            mine = rows[iterations - 1][slice(*borders[1][own : own + 2])]
            nbr, size = means.around(mine)
            x = np.zeros((n, len(mine)))
            x[nbr, np.repeat(np.arange(len(mine)), size)] = np.repeat(1.0 / np.maximum(size, 1), size)
            yield one(1, own, x)

    def go_on(k: int):
        def run(table: pa.Table) -> pa.Table:
            borders, own = shared.value[2], table["to"][0].as_py()
            low, high = borders[k][own : own + 2]
            x = np.zeros((borders[k - 1][-1], high - low))
            for sent, part in zip(table["sent"].to_pylist(), table["part"].to_pylist()):
                a, b = borders[k - 1][sent : sent + 2]
                x[a:b] = np.frombuffer(part).reshape(b - a, high - low)
            return pa.Table.from_batches([one(k, own, x)])

        return run

    cols, count = "to int, sent int, part binary", len(borders[1]) - 1
    out = spark.range(0, count, 1, count).mapInArrow(begin, cols)
    for k in range(2, iterations + 1):
        out = keep(out, "rows").repartition(len(borders[k]) - 1, "to").groupBy("to").applyInArrow(go_on(k), cols)
    found = keep(out, "rows").select("sent", "part").toArrow()
    score = np.frombuffer(b"".join(found["part"].to_pylist()))
    got = pa.table({"source": pa.array(np.full(len(score), source, np.int64)), "node": pa.array(ids[found["sent"].to_numpy()]), "score": pa.array(score)})
    return spark.createDataFrame(got, schema)


def _from_diagonals(adj: DataFrame, source: int, c: float, iterations: int) -> DataFrame:
    """source, node, score. With P the chances of steps, S after k iterations is the sum over t up to k of
    c**t P**t D(k - t) (P**t)' for diagonals D(j) that make the diagonal of S after j iterations ones: D(0) is 1,
    and D(j) of x is 1 less the sum over t from 1 to j of c**t P**t(x, y)**2 D(j - t) of y. The source's row
    needs D(k - t) only where walks of t steps from it may be, so an ancestor's rows of P**t are made
    up to t = k less its distance, and no pairs beyond them."""
    spark = adj.sparkSession
    far = _distances(adj, source, iterations)
    near = keep(adj.join(far, "node", "left_semi").select(F.col("node").alias("y"), "nbr", "node_deg"), "near")
    out = [spark.createDataFrame([(source, source, 1.0)], "x long, y long, m double")]
    for _ in range(iterations):
        out.append(keep(_places(out[-1], near), "out"))
    ahead = far.select(F.col("node").alias("x"), (F.lit(iterations) - F.col("distance")).cast("int").alias("left")).filter(F.col("left") > 0)
    rows = _squares(ahead, near, iterations) if near.count() <= TASK_EDGES else _squares_joined(ahead, near, iterations)
    diagonal: dict[int, DataFrame] = {}
    for j in range(1, iterations):
        # D(0) is 1, so the squares of the last step are summed where they are made
        mine = rows.join(ahead.filter(F.col("left") >= j).select("x"), "x", "left_semi")
        parts = [mine.filter((F.col("t") == j) & F.col("y").isNull()).select("x", (F.col("sq") * c**j).alias("s"))]
        for t in range(1, j):
            met = mine.filter(F.col("t") == t).join(diagonal[j - t].select(F.col("node").alias("y"), "d"), "y")
            parts.append(met.select("x", (F.col("sq") * F.col("d") * c**t).alias("s")))
        every = reduce(DataFrame.union, parts).groupBy("x").agg(F.sum("s").alias("s"))
        own = ahead.filter(F.col("left") >= j).join(every, "x", "left")
        diagonal[j] = keep(own.select(F.col("x").alias("node"), (F.lit(1.0) - F.coalesce("s", F.lit(0.0))).alias("d")), "diagonal")
    back = out[-1].select(F.col("y").alias("node"), "m")
    for t in range(iterations - 1, -1, -1):
        pulled = adj.join(back.select(F.col("node").alias("nbr"), "m"), "nbr").groupBy("node").agg((F.sum(F.col("m") / F.col("node_deg")) * c).alias("m"))
        if t:
            pulled = pulled.union(out[t].select(F.col("y").alias("node"), "m").join(diagonal[iterations - t], "node").select("node", F.col("m") * F.col("d"))).groupBy("node").agg(F.sum("m").alias("m"))
        back = keep(pulled, "back")
    rest = back.filter((F.col("node") != source) & (F.col("m") > 0)).select(F.lit(source).cast("long").alias("source"), "node", F.col("m").alias("score"))
    return rest.union(spark.createDataFrame([(source, source, 1.0)], "source long, node long, score double"))


def _places(rows: DataFrame, near: DataFrame) -> DataFrame:
    """x, y, m one step on: the chance that a walk of x is at y."""
    return rows.join(near, "y").groupBy("x", F.col("nbr").alias("y")).agg(F.sum(F.col("m") / F.col("node_deg")).alias("m"))


def _squares_joined(ahead: DataFrame, near: DataFrame, iterations: int) -> DataFrame:
    """``_squares`` by joins, for edges that no task holds."""
    at, parts = ahead.select("x", F.col("x").alias("y"), F.lit(1.0).alias("m")), []
    for t in range(1, iterations):
        at = keep(_places(at.join(ahead.filter(F.col("left") >= t).select("x"), "x", "left_semi"), near), "places")
        square = (F.col("m") * F.col("m")).alias("sq")
        longer = at.join(ahead.filter(F.col("left") > t).select("x"), "x", "left_semi")
        parts += [longer.select("x", F.lit(t).alias("t"), "y", square), at.select("x", square).groupBy("x").agg(F.sum("sq").alias("sq")).select("x", F.lit(t).alias("t"), F.lit(None).cast("long").alias("y"), "sq")]
    return reduce(DataFrame.union, parts) if parts else ahead.select("x", F.lit(0).alias("t"), F.col("x").alias("y"), F.lit(0.0).alias("sq")).limit(0)


def _squares(ahead: DataFrame, near: DataFrame, iterations: int) -> DataFrame:
    """x, t, y, sq: squares of the chances that a walk of x is at y after t steps, for t below ``left`` of x; with y null their
    sum over all y, for t up to ``left``. ``near`` comes to each task by an exchange, and rows stay there."""
    spark = ahead.sparkSession
    blocks = spark.sparkContext.defaultParallelism
    mine = ahead.withColumn("block", F.pmod(F.xxhash64("x"), F.lit(blocks)).cast("int")).repartition(8 * blocks, "block")
    # a row for each node, as every block gets all of them
    lists = near.groupBy("y").agg(F.collect_list("nbr").alias("nbr"))
    edges = lists.select(F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"), "y", "nbr").repartition(8 * blocks, "block")

    def run(own: pa.Table, edges: pa.Table) -> pa.Table:
        nbr, left = edges["nbr"].combine_chunks(), own["left"].to_numpy()
        begun, to = np.repeat(edges["y"].to_numpy(), np.asarray(nbr.value_lengths())), np.asarray(nbr.flatten())
        ids = np.unique(np.concatenate([np.unique(begun), np.unique(to), own["x"].to_numpy()]))
        n, order, at = len(ids), np.argsort(begun, kind="stable"), np.searchsorted(ids, own["x"].to_numpy())
        first = np.append(0, np.cumsum(np.bincount(np.searchsorted(ids, begun), minlength=n)))
        means, few, parts = _Means(first, np.searchsorted(ids, to).astype(np.int32)[order]), max(1, CELLS // max(1, n)), []
        del begun, to, order, edges, nbr
        for steps in np.unique(left):
            every = at[left == steps]
            for x in (every[k : k + few] for k in range(0, len(every), few)):
                i, y, m = np.arange(len(x)), x, np.ones(len(x))
                for t in range(1, steps + 1):
                    i, y, m = means.ahead(i, y, m, len(x), n)
                    sums = np.bincount(i, m * m, len(x))
                    parts.append((ids[x], np.full(len(x), t), np.zeros(len(x), np.int64), sums, np.ones(len(x), bool)))
                    if t < steps:
                        parts.append((ids[x[i]], np.full(len(i), t), ids[y], m * m, np.zeros(len(i), bool)))
        if not parts:
            parts = [(at[:0], at[:0], at[:0], np.zeros(0), np.zeros(0, bool))]
        x, t, y, sq, whole = (np.concatenate(z) for z in zip(*parts))
        return pa.table({"x": x, "t": pa.array(t, pa.int32()), "y": pa.array(y, mask=whole), "sq": sq})

    return keep(mine.groupBy("block").cogroup(edges.groupBy("block")).applyInArrow(run, "x long, t int, y long, sq double"), "squares")


def _distances(adj: DataFrame, source: int, longest: int) -> DataFrame:
    """node, distance: nodes where the source's walks may be after 1 up to ``longest`` - 1 steps, with the least number of
    them, and the source with ``longest`` if it is none of these."""
    ahead, seen = adj.sparkSession.createDataFrame([(source, 0)], "node long, distance int"), None
    for t in range(1, longest):
        found = ahead.join(adj, "node").select(F.col("nbr").alias("node"), F.lit(t).alias("distance")).distinct()
        ahead = keep(found if seen is None else found.join(seen, "node", "left_anti"), "ancestors")
        if ahead.isEmpty():
            break
        seen = ahead if seen is None else seen.union(ahead)
    own = adj.sparkSession.createDataFrame([(source, longest)], "node long, distance int")
    return own if seen is None else keep(seen.union(own.join(seen, "node", "left_anti")), "ancestors")


def local_matrix(edges: list[tuple[int, int]], nodes: list[int], c: float = 0.6, iterations: int = 30) -> np.ndarray:
    """The case of one machine: scores as a matrix in the order of ``nodes``."""
    at = {v: k for k, v in enumerate(nodes)}
    p = np.zeros((len(nodes), len(nodes)))
    for src, dst in set(edges):
        p[at[dst], at[src]] = 1.0
    deg = p.sum(1, keepdims=True)
    p = np.divide(p, deg, out=np.zeros_like(p), where=deg > 0)
    s = np.eye(len(nodes))
    for _ in range(iterations):
        s = c * p @ s @ p.T
        np.fill_diagonal(s, 1.0)
    return s


def closed_form_two_sided(g: Graph, c: float = 0.6) -> DataFrame:
    """a, b, score (a < b) on a directed graph whose sources have no in-neighbours: shared in-neighbours
    times c over the product of in-degrees."""
    side = _in(g, "u", "x", "du")
    pairs = side.join(side.select(F.col("u").alias("v"), "x", F.col("du").alias("dv")), "x").filter("u < v")
    return pairs.groupBy(F.col("u").alias("a"), F.col("v").alias("b"), "du", "dv").agg(F.count(F.lit(1)).alias("n")).select("a", "b", (F.lit(c) * F.col("n") / (F.col("du") * F.col("dv"))).alias("score"))


def expected_estimate(g: Graph, source: int, plan: SamplingPlan, normalization: str = "ideal") -> DataFrame:
    """source, node, score: the mean of the estimate over seeds. With f_t the chance that two unstopped
    walks first meet at step t (a difference of iterates over c**t), each estimator is a weighted
    sum of f_t."""
    r, last = math.sqrt(plan.c), plan.longest
    kept = [sum(plan.actual[t:]) for t in range(last + 1)]
    weights = {}
    for t in range(1, last + 1):
        if normalization == "plain":
            weights[t] = (kept[t] / plan.expected_total()) ** 2
        else:
            tail = r**t if plan.truncation == "clip" else r**t - r ** (last + 1)
            weights[t] = tail**2 * (plan.z / plan.expected_total() if normalization == "ideal" else 1.0)
    out = before = None
    for t, off in enumerate(iterates(g, plan.c, last), start=1):
        row = off.filter(F.col("a") == source).select("b", "score")
        grown = row if before is None else row.join(before.withColumnRenamed("score", "old"), "b", "left").select("b", (F.col("score") - F.coalesce("old", F.lit(0.0))).alias("score"))
        part = grown.select("b", (F.col("score") * (weights[t] / plan.c**t)).alias("score"))
        out, before = part if out is None else out.union(part), row
    return out.groupBy(F.lit(source).cast("long").alias("source"), F.col("b").alias("node")).agg(F.sum("score").alias("score"))
