"""Exact top-k by inner product with norm-bucketed retrieval.

Vectors are sorted by length and cut into buckets; queries come in blocks. A
query starts from a lower bound of its k-th score, found among the longest
vectors. In a bucket the bound becomes a local cosine threshold, bound divided
by the query's length and the bucket's greatest: above 1 the bucket is passed
over; if high, candidates are pruned by coordinates (a unit vector with cosine t
to the query lies, in coordinate f, within q_f t -+ sqrt((1 - t^2)(1 - q_f^2)) of
the cone's axis), else by length; what is left is verified with whole products.

Vectors become integers, floor(scale * x), and scores are exact integers.

Defined results: vectors that are null or hold null or non-finite components
take no part; a shorter vector counts as filled up with zeros; ties go to the
smaller id; null ids take no part; of rows with equal ids each is a candidate; an
empty table gives no rows; scores beyond 64 bits are held at the bounds.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import ship, stash

_LONG = 2**63 - 1


def _usable(df: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    v = F.col(vector_col)
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return df.filter(F.col(id_col).isNotNull() & v.isNotNull() & ~F.coalesce(bad, F.lit(True))).select(F.col(id_col).cast("long").alias("vec_id"), F.transform(v, lambda x: x.cast("double")).alias("v"))


def _matrix(column: pa.Array, scale: float) -> np.ndarray:
    """Rows of floor(scale * x); float64 if all are exact there, else Python integers."""
    lists = column.to_pylist() if column.null_count else None
    lengths = np.diff(np.asarray(column.offsets)) if lists is None else np.array([len(x) for x in lists])
    width = int(lengths.max(initial=0))
    flat = np.asarray(column.flatten(), dtype=np.float64)
    with np.errstate(over="ignore"):
        scaled = np.floor(scale * flat)
    if np.isfinite(scaled).all() and np.abs(scaled).max(initial=0) < 2**53:
        out = np.zeros((len(lengths), width))
    else:
        scaled = np.array([int(scale * 2**20) * (a := float(x).as_integer_ratio())[0] // (a[1] * 2**20) for x in flat.tolist()], object)
        out = np.zeros((len(lengths), width), object)
    out[np.arange(width) < lengths[:, None]] = scaled
    return out


def _products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact inner products of the rows of ``a`` and ``b``."""
    width = max(a.shape[1], b.shape[1])
    a, b = (np.pad(x, ((0, 0), (0, width - x.shape[1]))) if x.shape[1] < width else x for x in (a, b))
    if a.dtype != object and b.dtype != object:
        most = np.abs(a).max(initial=0) * np.abs(b).max(initial=0) * max(1, width)
        if most < 2**53:
            return a @ b.T
    return a.astype(object).dot(b.astype(object).T) if width else np.zeros((len(a), len(b)))


def _length(m: np.ndarray) -> np.ndarray:
    return np.sqrt((m.astype(np.float64) ** 2).sum(1))


class Bucket:
    """Vectors of similar length, longest first."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray):
        length = _length(rows)
        order = np.argsort(-length, kind="stable")
        self.ids, self.rows, self.length = ids[order], rows[order], length[order]
        self.unit = None
        self.sorted: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def by_length(self, need: float) -> int:
        """How many, from the front, are at least as long."""
        return int(np.searchsorted(-self.length, -need * (1 - 1e-9), "right"))

    def by_coordinate(self, q: np.ndarray, cosine: float, focus: int) -> np.ndarray:
        """Rows that reach ``cosine`` with unit vector ``q`` as far as ``focus`` coordinates tell."""
        if self.unit is None:
            self.unit = self.rows.astype(np.float64) / np.maximum(self.length, 1e-300)[:, None]
        found = None
        for f in np.argsort(-np.abs(q), kind="stable")[:focus].tolist():
            if f >= self.unit.shape[1]:
                continue
            if f not in self.sorted:
                by = np.argsort(self.unit[:, f], kind="stable")
                self.sorted[f] = (by, self.unit[by, f])
            by, values = self.sorted[f]
            x = float(np.clip(q[f], -1, 1))
            spread = np.sqrt((1 - cosine**2) * (1 - x * x))
            # the cone's extremes: the axis itself where the pole of the coordinate is inside
            low = -1.0 if -x >= cosine else x * cosine - spread
            high = 1.0 if x >= cosine else x * cosine + spread
            a, b = np.searchsorted(values, low - 1e-9), np.searchsorted(values, high + 1e-9, "right")
            own = by[a:b]
            found = own if found is None else found[np.isin(found, own)]
        return np.arange(len(self.ids)) if found is None else found


def _best(ids: np.ndarray, scores: np.ndarray, k: int, own: int) -> tuple[np.ndarray, np.ndarray]:
    """The k highest scores, ties to smaller ids, without candidates of id ``own``."""
    keep = np.flatnonzero(ids != own)
    if len(keep) > 4 * k:
        s = scores[keep]
        least = np.partition(s, len(s) - k)[len(s) - k]
        keep = keep[s >= least]
    order = keep[np.lexsort((ids[keep], -scores[keep]))][:k]
    return ids[order], scores[order]


def search_bucket(bucket: Bucket, query_ids: np.ndarray, queries: np.ndarray, bound: np.ndarray, k: int, high: float = 0.9, focus: int = 4):
    """(place of the query, ids, scores) of each query's best in the bucket; ``bound``: what a score
    must reach to matter (-inf: none yet)."""
    size = _length(queries)
    longest = bucket.length[0] if len(bucket.length) else 0.0
    with np.errstate(divide="ignore", invalid="ignore"):
        cosine = np.where((size > 0) & (longest > 0), bound / (size * longest), np.where(bound > 0, np.inf, -np.inf))
    everything = np.flatnonzero(cosine <= 0)
    if len(everything):
        scores = _products(queries[everything], bucket.rows)
        for q, s in zip(everything, scores):
            yield (q, *_best(bucket.ids, s, k, query_ids[q]))
    some = np.flatnonzero((cosine > 0) & (cosine <= 1 + 1e-9))
    steep = cosine[some] >= high
    flat = some[~steep]
    if len(flat):
        n = max(bucket.by_length(bound[q] / size[q]) for q in flat)
        scores = _products(queries[flat], bucket.rows[:n])
        for q, s in zip(flat, scores):
            m = bucket.by_length(bound[q] / size[q])
            yield (q, *_best(bucket.ids[:m], s[:m], k, query_ids[q]))
    for q in some[steep]:
        rows = bucket.by_coordinate(queries[q].astype(np.float64) / size[q], min(1.0, cosine[q] * (1 - 1e-9)), focus)
        yield (q, *_best(bucket.ids[rows], _products(queries[q : q + 1], bucket.rows[rows])[0], k, query_ids[q]))


def _pack(batches: Iterator[pa.RecordBatch], ids: str, most: int) -> Iterator[tuple[list, list]]:
    held_ids, held_rows = [], []
    for b in batches:
        for i, v in zip(b.column(ids).to_pylist(), b.column("v").to_pylist()):
            held_ids.append(i)
            held_rows.append(v)
            if len(held_ids) == most:
                yield held_ids, held_rows
                held_ids, held_rows = [], []
    if held_ids:
        yield held_ids, held_rows


def _blocks(most: int):
    """Rows of a partition as packed blocks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, rows in _pack(batches, "vec_id", most):
            yield pa.RecordBatch.from_arrays([pa.array([ids], pa.list_(pa.int64())), pa.array([rows], pa.list_(pa.list_(pa.float64())))], ["ids", "rows"])

    return run


def top_k(df: DataFrame, is_query: Column, k: int = 5, scale: float = 256.0, id_col: str = "vec_id", vector_col: str = "embedding", block: int = 2048, seeds: int = 1024) -> DataFrame:
    """query_id, rank (from 1), vec_id, score: for every row that fits ``is_query`` the ``k`` rows of
    other ids with the highest inner products. ``seeds``: how many of the longest vectors give the
    first bounds (a constant, sent to all)."""
    ship(df.sparkSession)
    rows = stash(_usable(df, id_col, vector_col).withColumn("size", F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)), "vectors")
    queries = rows.filter(is_query).select("vec_id", "v")
    first = [(r["vec_id"], r["v"]) for r in rows.orderBy(F.desc("size"), "vec_id").select("vec_id", "v").limit(seeds).collect()]
    seed_ids = np.array([i for i, _ in first], np.int64)
    seed_rows = _matrix(pa.array([v for _, v in first], pa.list_(pa.float64())), scale)

    def with_bounds(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, vectors in _pack(batches, "vec_id", block):
            q = _matrix(pa.array(vectors, pa.list_(pa.float64())), scale)
            scores = _products(q, seed_rows)
            bounds = []
            for i, s in zip(ids, scores):
                s = s[seed_ids != i]
                bounds.append(float(np.partition(s, len(s) - k)[len(s) - k]) if len(s) >= k else -np.inf)
            yield pa.RecordBatch.from_arrays([pa.array([ids], pa.list_(pa.int64())), pa.array([vectors], pa.list_(pa.list_(pa.float64()))), pa.array([bounds], pa.list_(pa.float64()))], ["qids", "qrows", "bounds"])

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(b.num_rows):
                bucket = Bucket(np.asarray(b.column("ids")[at].values), _matrix(b.column("rows")[at].values, scale))
                asking, bounds = (np.asarray(b.column(c)[at].values) for c in ("qids", "bounds"))
                out = search_bucket(bucket, asking, _matrix(b.column("qrows")[at].values, scale), bounds, k)
                found = [(int(asking[q]), i, max(-_LONG - 1, min(_LONG, int(s)))) for q, ids, scores in out for i, s in zip(ids.tolist(), scores.tolist()) if s >= bounds[q]]
                if found:
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found)], ["query_id", "vec_id", "score"])

    asked = queries.mapInArrow(with_bounds, "qids array<long>, qrows array<array<double>>, bounds array<double>")
    buckets = rows.repartitionByRange(F.desc("size"), "vec_id").sortWithinPartitions(F.desc("size"), "vec_id").select("vec_id", "v").mapInArrow(_blocks(block), "ids array<long>, rows array<array<double>>")
    # blocks of queries meet buckets: the stated query set against all rows
    found = asked.crossJoin(buckets).mapInArrow(join, "query_id long, vec_id long, score long")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
