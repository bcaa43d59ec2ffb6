"""Bulk-synchronous best-fit packing.

Only a document longer than a sequence is cut. Lengths are taken in bands from long
to short. In a round, the band's waiting pieces and the gaps of all open
sequences are range-sorted together, the largest first, and each task sweeps its own
range: a piece takes the least gap that holds it, its successor, and what is left of the
gap stays in the sweep; of pieces that have the same successor the higher rank gets it.
Pieces and gaps that are left over meet by their ranks in the carries between
tasks, for which the driver has some numbers of each task. Gaps are updated and the round is
repeated as long as a gap that changed can hold a piece that waits. What is left then
opens sequences: ranks are grouped, as many neighbours a sequence as it holds.

Every round is written to the shared folder.

Defined results: null text is the empty document (one token: the separator);
rows with equal ids are packed as separate documents; an empty table gives no
rows.
"""

from __future__ import annotations

import bisect
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import word_bpe
from .common import documents, ship, slices, stash, task_id

_OF_PIECE = "doc_id long, piece int, start long, length int, ids_crc32 long"
_PIECES = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int32()), ("ids_crc32", pa.int64())])
_OWN = _PIECES.names


def _cut(tokenizer_path: str, capacity: int, separator: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = word_bpe.load(tokenizer_path)
        tail, step = np.array([separator], "<u4").tobytes(), 4 * capacity
        for batch in slices(batches, most=4 << 20):
            rows = []
            ids, off = bpe.encode(batch.column("text"))
            for doc, a, b in zip(batch.column("doc_id").to_pylist(), off.tolist(), off[1:].tolist()):
                own = ids[a:b].tobytes() + tail
                for k, at in enumerate(range(0, len(own), step)):
                    part = own[at : at + step]
                    rows.append((doc, k, at // 4, len(part) // 4, zlib.crc32(part)))
            yield pa.record_batch([pa.array(c, f.type) for c, f in zip(zip(*rows), _PIECES)], schema=_PIECES)

    return run


def plan_classes(counts: dict[int, int], capacity: int) -> tuple[np.ndarray, int]:
    """Places for ``counts`` pieces of each length: rows (length, first rank, first sequence, pieces
    a sequence, first offset), by length and rank, and the number of sequences. The pieces of a row
    from its first rank to the next row's fill one sequence after another.

    Longest first; a run of sequences with equal gaps takes one class at a time, and a sequence
    takes as many pieces of the class as it holds, for its gap stays the least that fits."""
    runs: dict[int, list[tuple[int, int]]] = {}  # by gap: first sequence and number of sequences
    gaps: list[int] = []
    rows, sequences = [], 0

    def put(gap: int, first: int, n: int) -> None:
        if gap and n:
            if gap not in runs:
                runs[gap] = []
                bisect.insort(gaps, gap)
            runs[gap].append((first, n))

    for length in sorted(counts, reverse=True):
        left, rank = counts[length], 0
        while left:
            at = bisect.bisect_left(gaps, length)
            if at == len(gaps):
                n = -(-left // (capacity // length))
                put(capacity, sequences, n)
                sequences += n
                continue
            gap = gaps[at]
            first, n = runs[gap].pop()
            if not runs[gap]:
                del runs[gap], gaps[at]
            each = gap // length
            used = min(n, -(-left // each))
            placed = min(left, used * each)
            rows.append((length, rank, first, each, capacity - gap))
            full, over = divmod(placed, each)
            put(gap - each * length, first, full)
            if over:
                put(gap - over * length, first + full, 1)
            put(gap, first + used, n - used)
            left -= placed
            rank += placed
    return np.array(sorted(rows), np.int64).reshape(-1, 5), sequences

def bands(capacity: int, harmonic: int = 6, halves: int = 5) -> list[tuple[int, int]]:
    """(longest, next band's longest): up to ``harmonic`` pieces of a band fill a sequence, then halves,
    then all that is shorter."""
    edge = [capacity // k for k in range(1, harmonic + 1)]
    edge += [edge[-1] >> k for k in range(1, halves + 1)]
    edge = list(dict.fromkeys(e for e in edge if e))
    return list(zip(edge, [*edge[1:], 0]))


_GAP, _PIECE = 0, 1
_HIT, _WAITS, _FREE, _REST, _SUMS = range(5)  # placed; a piece or a gap for the carries; a gap too small for them; a task's sums
_SWEPT = pa.schema([("state", pa.int32()), ("task", pa.int32()), ("rank", pa.int64()), ("bin", pa.int64()), ("gap", pa.int32()), *_PIECES, ("sums", pa.list_(pa.int64()))])
_SWEPT_SQL = f"state int, task int, rank long, bin long, gap int, {_OF_PIECE}, sums array<long>"


def sweep(kind: np.ndarray, size: np.ndarray) -> tuple[list[int], list[int], list[int], list[tuple[int, int]], set[int]]:
    """Of gaps and pieces in falling order of size: pieces that are placed and the gaps (by place) they go
    to, in order; pieces that wait; (size, gap) of what is left of gaps, the largest first; and
    which gaps have changed. A piece takes the least gap that holds it, whole or what is left of it."""
    open_: list[tuple[int, int]] = []  # (-size, gap), so the end is the least
    hits, gaps, waits, changed = [], [], [], set()
    for at, (k, n) in enumerate(zip(kind.tolist(), size.tolist())):
        if k == _GAP:
            bisect.insort(open_, (-n, at))
            continue
        fit = bisect.bisect_right(open_, (-n, len(kind))) - 1
        if fit < 0:
            waits.append(at)
            continue
        left, gap = open_.pop(fit)
        hits.append(at)
        gaps.append(gap)
        changed.add(gap)
        if left + n:
            bisect.insort(open_, (left + n, gap))
    return hits, gaps, waits, [(-n, gap) for n, gap in open_], changed


def _sweep(capacity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        rows = pa.Table.from_batches(held).combine_chunks().to_batches()[0]
        size = np.asarray(rows.column("size"))
        hits, gaps, waits, left, changed = sweep(np.asarray(rows.column("kind")), size)
        free = sum(n >= size[-1] for n, _ in left)  # these hold whatever later tasks have
        wait = size[waits]
        holds, first = np.unique(capacity // wait, return_index=True) if len(wait) else (wait, wait)
        most = max((n for n, gap in left[free:] if gap in changed), default=0)
        sums = [len(hits), len(waits), free, left[free - 1][0] if free else 0, wait[0] if len(wait) else 0, wait[-1] if len(wait) else 0, most, *(x for pair in zip(holds.tolist(), first.tolist()) for x in pair)]
        counts = [len(hits), len(waits), free, len(left) - free, 1]
        piece, gap = (rows.take(pa.array(x, pa.int64())) for x in ([*hits, *waits, *([0] * (len(left) + 1))], [*gaps, *([0] * len(waits)), *(g for _, g in left), 0]))
        state = np.repeat(np.arange(5, dtype=np.int32), counts)
        rank = np.concatenate([np.arange(n) for n in counts])
        task = np.full(len(state), task_id(), np.int32)
        now = np.concatenate([np.zeros(len(hits) + len(waits)), [n for n, _ in left], [0]]).astype(np.int32)
        yield pa.RecordBatch.from_arrays([pa.array(state), pa.array(task), pa.array(rank), gap.column("bin"), pa.array(now), *(piece.column(c) for c in _OWN), pa.array([None] * (len(state) - 1) + [sums], pa.list_(pa.int64()))], schema=_SWEPT)

    return run


def carries(waits: list[int], free: list[int], each=lambda task, before: 1) -> list[tuple[int, int, int, int, int, int]]:
    """Which ranks of what tasks left over meet: (task of pieces, first rank, task of gaps, last rank,
    pieces, pieces a gap). Pieces rise through their ranks as gaps fall, for the nearest gap is
    the last one of the nearest task before."""
    open_: list[list[int]] = []
    out = []
    for task, (n, m) in enumerate(zip(waits, free)):
        at = 0
        while at < n and open_:
            before, last = open_[-1]
            k = each(task, before)
            both = min(n - at, (last + 1) * k)
            out.append((task, at, before, last, both, k))
            at += both
            open_[-1][1] -= -(-both // k)
            if open_[-1][1] < 0:
                open_.pop()
        if m:
            open_.append([task, m - 1])
    return out


def _numbers(met: list[tuple[int, int, int, int, int, int]]):
    """Pieces and gaps left over with the number of their meeting, or null."""
    of: dict[tuple[int, int], list[tuple[int, int, int, int]]] = {}
    number = 0
    for task, rank, before, last, n, k in met:
        of.setdefault((_WAITS, task), []).append((rank, n, k, number))
        of.setdefault((_FREE, before), []).append((last, -(-n // k), 0, number))
        number += -(-n // k)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            state, task, rank = (np.asarray(b.column(c)) for c in ("state", "task", "rank"))
            number = np.full(b.num_rows, -1, np.int64)
            for s, t in set(zip(state.tolist(), task.tolist())):
                mine = np.flatnonzero((state == s) & (task == t))
                for first, n, k, base in of.get((s, t), ()):
                    nth = rank[mine] - first if k else first - rank[mine]
                    hit = (nth >= 0) & (nth < n)
                    number[mine[hit]] = base + nth[hit] // max(1, k)
            yield pa.RecordBatch.from_arrays([pa.array(number, mask=number < 0), *b.columns], ["number", *b.schema.names])

    return run


def _meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by number, a gap and then its pieces: the pieces with their sequence, and what is
    left of the gap."""
    bin_ = gap = number = None
    for b in batches:
        rows, out = b.to_pydict(), []
        for k, now in enumerate(rows["number"]):
            if rows["state"][k] == _FREE:
                if gap:
                    out.append((bin_, gap, None, *[None] * len(_OWN)))
                number, bin_, gap = now, rows["bin"][k], rows["gap"][k]
            else:
                assert now == number
                gap -= rows["length"][k]
                out.append((bin_, None, rows["rank"][k], *(rows[c][k] for c in _OWN)))
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), (pa.int64(), pa.int32(), pa.int64(), *_PIECES.types))], ["bin", "gap", "nth", *_OWN])
    if gap:
        yield pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip((bin_, gap, None, *[None] * len(_OWN)), (pa.int64(), pa.int32(), pa.int64(), *_PIECES.types))], ["bin", "gap", "nth", *_OWN])


def _still(carried: dict[int, int]):
    """Waiting pieces that the carries have not placed: of each task, those from its number on."""
    task_of = np.array(sorted(carried), np.int64)
    first_of = np.array([carried[t] for t in task_of.tolist()], np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            task, rank = np.asarray(b.column("task")), np.asarray(b.column("rank"))
            first = np.zeros(b.num_rows, np.int64)
            if len(task_of):
                at = np.minimum(np.searchsorted(task_of, task), len(task_of) - 1)
                first = np.where(task_of[at] == task, first_of[at], 0)
            yield b.select(_OWN).filter(pa.array(rank >= first))

    return run


def _opened(start: dict[tuple[int, int], tuple[int, int]], bin_of: dict[int, int], capacity: int):
    """Places of waiting pieces in sequences that they open. Of a task and a class (how many of its pieces a
    sequence holds), ``start`` has the first rank in the task and its rank in the class."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            task, nth = np.asarray(b.column("task")), np.asarray(b.column("rank"))
            holds = capacity // np.asarray(b.column("length")).astype(np.int64)
            bin_, place = np.zeros(b.num_rows, np.int64), np.full(b.num_rows, -1, np.int64)
            for t, h in set(zip(task.tolist(), holds.tolist())):
                if (t, h) not in start:
                    continue
                first, base = start[t, h]
                mine = np.flatnonzero((task == t) & (holds == h) & (nth >= first))
                rank = base + nth[mine] - first
                bin_[mine], place[mine] = bin_of[h] + rank // h, rank % h
            out = pa.RecordBatch.from_arrays([pa.array(bin_), pa.array(place), *(b.column(c) for c in _OWN)], ["bin", "nth", *_OWN])
            yield out.filter(pa.array(place >= 0))

    return run


def _dealt(df: DataFrame, tasks: int, *keys) -> DataFrame:
    """Rows with equal keys in one task, of ``tasks``. One task needs no exchange."""
    return df.repartition(tasks, *keys) if tasks > 1 else df.coalesce(1)


def _ranged(df: DataFrame, tasks: int, order: list) -> DataFrame:
    """Globally sorted into ``tasks`` ranges. One task needs no exchange."""
    return (df.repartitionByRange(tasks, *order) if tasks > 1 else df.coalesce(1)).sortWithinPartitions(*order)


class _Packing:
    """Gaps of open sequences (bin, gap) and what has been placed: (bin, turn, nth, piece)."""

    def __init__(self, capacity: int, rows_a_task: int):
        self.capacity, self.rows_a_task = capacity, rows_a_task
        self.gaps: DataFrame | None = None
        self.bins = self.turn = 0
        self.placed: list[DataFrame] = []

    def take(self, found: DataFrame) -> None:
        self.placed.append(found.select("bin", F.lit(self.turn).alias("turn"), F.col("nth").cast("long").alias("nth"), *_OWN))
        self.turn += 1

    def round(self, waiting: DataFrame, n: int) -> tuple[DataFrame, dict, dict[int, int], int, bool]:
        """Match ``n`` waiting pieces with the gaps: the swept rows, the sums of each task, how many of
        its waiting pieces the carries have placed, how many wait, and whether another round may
        place some."""
        none = [F.lit(None).cast(f.split()[1]).alias(f.split()[0]) for f in _OF_PIECE.split(", ")]
        tokens = waiting.select(F.col("length").alias("size"), F.lit(_PIECE).alias("kind"), F.lit(None).cast("long").alias("bin"), *_OWN)
        if self.gaps is not None:
            tokens = tokens.unionByName(self.gaps.select(F.col("gap").alias("size"), F.lit(_GAP).alias("kind"), "bin", *none))
        order = [F.desc("size"), F.asc("kind"), F.asc("bin"), F.asc("doc_id"), F.asc("start"), F.asc("ids_crc32")]
        tasks = max(1, -(-(n + self.bins) // self.rows_a_task))
        swept = stash(_ranged(tokens, tasks, order).mapInArrow(_sweep(self.capacity), _SWEPT_SQL), "swept")
        sums = {r["task"]: r["sums"] for r in swept.filter(F.col("state") == _SUMS).select("task", "sums").collect()}  # one row a task
        every = range(1 + max(sums))
        of = lambda t, k: sums[t][k] if t in sums else 0
        met = carries([of(t, 1) for t in every], [of(t, 2) for t in every], lambda task, before: max(1, of(before, 3) // of(task, 4)))
        self.take(swept.filter(F.col("state") == _HIT).withColumnRenamed("rank", "nth"))
        gaps = swept.filter(F.col("state").isin(_FREE, _REST)).select("bin", "gap")
        carried: dict[int, int] = {}
        if met:
            over = swept.filter(F.col("state").isin(_WAITS, _FREE)).mapInArrow(_numbers(met), f"number long, {_SWEPT_SQL}")
            pairs = _dealt(over.filter("number is not null"), tasks, "number").sortWithinPartitions("number", F.desc("state"), "rank")
            both = stash(pairs.select("number", "state", "bin", "gap", "rank", *_OWN).mapInArrow(_meet, f"bin long, gap int, nth long, {_OF_PIECE}"), "carried")
            self.take(both.filter("length is not null"))
            unmet = over.filter((F.col("state") == _FREE) & F.col("number").isNull()).select("bin", "gap")
            gaps = unmet.unionByName(swept.filter(F.col("state") == _REST).select("bin", "gap")).unionByName(both.filter("length is null").select("bin", "gap"))
            for task, _, _, _, n_met, _ in met:
                carried[task] = carried.get(task, 0) + n_met
        self.gaps = gaps
        left = {t: x[1] - carried.get(t, 0) for t, x in sums.items()}
        least = min((x[5] for t, x in sums.items() if left[t]), default=0)
        placed = n - sum(left.values())
        again = 100 * placed >= n and (bool(met) or any(x[6] >= least for x in sums.values()))
        return swept, sums, carried, sum(left.values()), again

    def band(self, waiting: DataFrame, n: int) -> None:
        while True:
            swept, sums, carried, n, again = self.round(waiting, n)
            if not n:
                return
            if not again:
                break
            waiting = swept.filter(F.col("state") == _WAITS).mapInArrow(_still(carried), _OF_PIECE)
        start, total = {}, {}
        for task in sorted(sums):
            classes = list(zip(sums[task][7::2], [*sums[task][8::2]]))
            for (h, first), (_, end) in zip(classes, [*classes[1:], (0, sums[task][1])]):
                first = max(first, carried.get(task, 0))
                if end > first:
                    start[task, h] = (first, total.get(h, 0))
                    total[h] = total.get(h, 0) + end - first
        bin_of = {}
        for h in sorted(total):
            bin_of[h] = self.bins
            self.bins += -(-total[h] // h)
        found = stash(swept.filter(F.col("state") == _WAITS).mapInArrow(_opened(start, bin_of, self.capacity), f"bin long, nth long, {_OF_PIECE}"), "opened")
        self.take(found)
        tasks = max(1, -(-n // self.rows_a_task))
        gaps = _dealt(found, tasks, "bin").groupBy("bin").agg((F.lit(self.capacity) - F.sum("length")).cast("int").alias("gap")).filter("gap > 0")
        self.gaps = gaps if self.gaps is None else self.gaps.unionByName(gaps)


def pack(df: DataFrame, tokenizer_path: str, capacity: int = 2048, separator: int = 0, id_col: str = "doc_id", text_col: str = "text", rows_a_task: int = 100_000) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset: one row for every piece.
    ``rows_a_task``: pieces and gaps that a task sweeps."""
    ship(df.sparkSession)
    pieces = stash(documents(df, id_col, text_col).mapInArrow(_cut(tokenizer_path, capacity, separator), _OF_PIECE), "pieces")
    return place(pieces, capacity, rows_a_task)


def place(pieces: DataFrame, capacity: int, rows_a_task: int = 100_000) -> DataFrame:
    """``pieces`` (doc_id, piece, start, length, ids_crc32) with sequence_id and offset."""
    ship(pieces.sparkSession)
    pieces = pieces.select(*(F.col(f.split()[0]).cast(f.split()[1]) for f in _OF_PIECE.split(", ")))
    cuts = bands(capacity)
    band = F.lit(len(cuts) - 1)
    for k, (_, under) in reversed(list(enumerate(cuts))[:-1]):
        band = F.when(F.col("length") > under, k).otherwise(band)
    counts = pieces.agg(*(F.count_if(band == k).alias(str(k)) for k in range(len(cuts)))).first()
    seen = {k: counts[str(k)] for k in range(len(cuts)) if counts[str(k)]}
    tasks = max(1, -(-sum(seen.values()) // rows_a_task))
    by_length = [F.desc("length"), F.asc("doc_id"), F.asc("start")]
    pieces = stash(_ranged(pieces, tasks, by_length), "by-length")  # a band reads its own files
    state = _Packing(capacity, rows_a_task)
    for k, (longest, under) in enumerate(cuts):
        if k in seen:
            state.band(pieces.filter((F.col("length") <= longest) & (F.col("length") > under)), seen[k])
    if not state.placed:
        return pieces.select(*_OWN[:3], F.col("length").cast("long").alias("length"), "ids_crc32", F.lit(0).cast("long").alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    every = state.placed[0]
    for more in state.placed[1:]:
        every = every.unionByName(more)
    every = _dealt(every, tasks, "bin")
    before = Window.partitionBy("bin").orderBy("turn", "nth").rowsBetween(Window.unboundedPreceding, -1)
    offset = F.coalesce(F.sum("length").over(before), F.lit(0)).cast("long")
    return every.select("doc_id", "piece", "start", F.col("length").cast("long").alias("length"), "ids_crc32", F.col("bin").alias("sequence_id"), offset.alias("offset"))
