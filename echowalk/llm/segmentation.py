"""SentencePiece encoding by Gumbel top-k sampling without replacement, and decoding.

All segmentations of a text are paths of a lattice of pieces; a path's
probability is the product of its pieces' weights over the lattice's sum.
Each path's log-probability is perturbed by Gumbel noise, and the k paths with
the greatest perturbed values are a sample without replacement. They are found
without listing paths: a best-first (A*) search whose nodes are sets of paths
with a common beginning. The suffix sums give a set's exact mass, so its greatest
perturbed value can be drawn before its paths are (a Gumbel truncated at the
parent's), and that value is the search's bound. Taking a path splits its set at
every choice along it into what else could have been chosen there.

The next value after the k-th is the threshold of the sample: a path's inclusion
score is the probability that its value passes it.

Draws are hashes of the seed, the row key and the place in the text, so a row's
samples do not depend on partitions or retries.

Defined results: null and empty texts have one segmentation, without pieces;
texts with fewer segmentations than k give them all, with inclusion 1; rows with
equal ids and texts get equal samples, null ids count as the least long; an empty
table gives no rows.
"""

from __future__ import annotations

import math
import zlib
from bisect import bisect_right
from collections.abc import Iterator
from functools import lru_cache
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import documents, mix, ship, slices

_U = np.uint64
_ALL = 2**64 - 1
_MARK = "▁"


def _longer(h: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """Hashes of strings that are one character longer. No step is linear in the one before."""
    h = (h ^ codes.astype(_U)) * _U(0x9E3779B97F4A7C15)
    return h ^ (h >> _U(29))


class Pieces:
    """A model's pieces with log-weights. Models trained as BPE have ranks for scores; theirs become
    Zipf weights (1 / (rank + 2.7)). Texts are taken as they are, with a blank put before them."""

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        if "".join(model.encode("a  \tb ", out_type=str)).replace("<0x09>", "\t") != f"{_MARK}a{_MARK}{_MARK}\tb{_MARK}":
            raise ValueError("only models that take texts as they are, after a blank, are handled")
        n = model.vocab_size()
        normal = [i for i in range(n) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i))]
        score = np.array([model.get_score(i) for i in normal])
        usual = score > -1e8  # user-defined runs of blanks have no rank: they come last
        if (score[usual] == np.round(score[usual])).all():
            rank = np.where(usual, -score, n)
            weight = -np.log(rank + 2.7)
        else:
            weight = np.where(usual, score, score[usual].min())
        self.total = np.log(np.exp(weight).sum())
        weight = weight - self.total
        texts = [model.id_to_piece(i) for i in normal]
        self.longest = max(map(len, texts))
        h, size = np.zeros(len(texts), _U), np.array([len(t) for t in texts])
        for at in range(self.longest):
            some = np.flatnonzero(size > at)
            h[some] = _longer(h[some], np.array([ord(texts[k][at]) for k in some.tolist()]))
        order = np.argsort(h)
        self.hash, self.id, self.weight = h[order], np.array(normal, np.int64)[order], weight[order]
        if (self.hash[1:] == self.hash[:-1]).any():
            raise ValueError("two pieces share a hash")
        self.slots, left = [], np.arange(len(self.hash))
        while len(left):  # a piece whose slot is taken goes to the next table
            table = np.full(1 << 20, -1, np.int32)
            slot, first = np.unique(self._slot(self.hash[left], len(self.slots)), return_index=True)
            table[slot] = left[first]
            left = np.delete(left, first)
            self.slots.append(table)
        self.byte_id = np.full(256, model.unk_id(), np.int64)
        for i in range(n):
            if model.is_byte(i):
                self.byte_id[int(model.id_to_piece(i)[3:-1], 16)] = i
        self.byte_weight = float(weight.min()) - 1.0
        said = [bytes([int(model.id_to_piece(i)[3:-1], 16)]) if model.is_byte(i) else b"" if model.is_control(i) else model.id_to_piece(i).replace(_MARK, " ").encode() for i in range(n)]
        self.bytes = np.frombuffer(b"".join(said), np.uint8)
        self.bytes_from = np.concatenate([[0], np.cumsum([len(s) for s in said])])

    @staticmethod
    def _slot(h: np.ndarray, table: int) -> np.ndarray:
        return (h >> _U(max(0, 44 - 12 * table))) & _U((1 << 20) - 1)

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which of the hashes are pieces' (as indices), and the pieces' places."""
        out = self.slots[0][self._slot(h, 0)]
        likely = np.flatnonzero(out >= 0)
        place, h = out[likely], h[likely]
        for n in range(1, len(self.slots)):
            wrong = np.flatnonzero(self.hash[place] != h)
            other = self.slots[n][self._slot(h[wrong], n)]
            place[wrong[other >= 0]] = other[other >= 0]
        right = self.hash[place] == h
        return likely[right], place[right]

    def decode(self, ids: np.ndarray) -> bytes:
        ids = np.asarray(ids, np.int64)
        at = _ranges(self.bytes_from[ids], self.bytes_from[ids + 1] - self.bytes_from[ids])
        out = self.bytes[at].tobytes()
        return out[1:] if out[:1] == b" " else out


@lru_cache(2)
def load(path: str) -> Pieces:
    return Pieces(path)


def _ranges(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    return np.repeat(start - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))


class Lattice:
    """Edges between the character positions of distinct chunks (a blank or several and what
    follows up to the next), each with its probability given that its start is reached."""

    def __init__(self, pieces: Pieces, texts: list[str], smooth: float):
        starts = np.concatenate([[0], np.cumsum([len(t) + 1 if t else 0 for t in texts])])
        codes = np.frombuffer("".join(_MARK + t.replace(" ", _MARK) for t in texts if t).encode("utf-32-le", "surrogatepass"), np.uint32)
        blank = codes == ord(_MARK)
        opens = blank.copy()
        opens[1:] &= ~blank[:-1]
        opens[starts[:-1][np.diff(starts) > 0]] = True
        chunk = np.flatnonzero(opens)
        ends = np.concatenate([chunk[1:], [len(codes)]]) if len(chunk) else chunk
        self.first_chunk = np.searchsorted(chunk, starts)
        held = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(chunk), [None, pa.py_buffer(4 * np.append(chunk, len(codes)).astype(np.int64)), pa.py_buffer(codes)])
        coded = held.dictionary_encode()  # tells chunks by comparing them
        self.kind = np.asarray(coded.indices).astype(np.int64)
        sample = np.zeros(len(coded.dictionary), np.int64)
        sample[self.kind[::-1]] = np.arange(len(chunk))[::-1]
        size = ends[sample] - chunk[sample]
        own = codes[_ranges(chunk[sample], size)]
        self.origin = np.concatenate([[0], np.cumsum(size)])[:-1]  # where each kind of chunk starts in ``own``
        left = np.repeat(self.origin + size, size) - np.arange(len(own))  # characters up to the chunk's end
        self.left = np.append(left, 0)
        at, length, piece, weight = [], [], [], []
        position, h = np.arange(len(own)), np.zeros(len(own), _U)
        for n in range(1, pieces.longest + 1):
            if n > 1:
                on = left[position] >= n
                position, h = position[on], h[on]
            if not len(position):
                break
            h = _longer(h, own[position + n - 1])
            hit, k = pieces.find(h)
            at.append(position[hit])
            length.append(np.full(len(k), n))
            piece.append(pieces.id[k])
            weight.append(pieces.weight[k] * smooth)
        bare = np.ones(len(own), bool)
        if at:
            bare[at[0]] = False
        bare = np.flatnonzero(bare)  # characters that are no piece: as bytes
        chars = own[bare]
        width = 1 + (chars > 0x7F).astype(np.int64) + (chars > 0x7FF) + (chars > 0xFFFF)
        at.append(bare)
        length.append(np.ones(len(bare), np.int64))
        piece.append(-1 - chars.astype(np.int64))
        weight.append(width * pieces.byte_weight * smooth)
        at, length, piece, weight = (np.concatenate(x) for x in (at, length, piece, weight))
        order = np.argsort(at * 64 - length, kind="stable")  # by start, the longest first
        self.at, self.to, self.piece, weight = at[order], (at + length)[order], piece[order], weight[order]
        # a chunk's last position leads to 0, whichever chunk's first position has its number
        rest = np.zeros(len(own) + 1)
        from_end = self.left[self.at]
        by = np.argsort(from_end.astype(np.int16) if from_end.max(initial=0) < 1 << 15 else from_end, kind="stable")
        turn = np.searchsorted(from_end[by], np.arange(1, (from_end.max() if len(by) else 0) + 2))
        ends_here = from_end == self.to - self.at
        for a, b in zip(turn[:-1], turn[1:]):
            e = by[a:b]
            if not len(e):
                continue
            v = weight[e] + np.where(ends_here[e], 0.0, rest[self.to[e]])
            new = np.flatnonzero(np.concatenate([[True], self.at[e][1:] != self.at[e][:-1]]))
            top = np.maximum.reduceat(v, new)
            total = np.log(np.add.reduceat(np.exp(v - np.repeat(top, np.diff(np.append(new, len(e))))), new)) + top
            rest[self.at[e][new]] = total
        self.ends_here = ends_here
        self.log_p = weight + np.where(ends_here, 0.0, rest[self.to]) - rest[self.at]
        self.first_edge = np.searchsorted(self.at, np.arange(len(own) + 1))
        p = np.exp(self.log_p)
        small = np.where(p > 0.5, 0.0, p)  # all else at the start of an edge of over 0.5 is these; nothing cancels
        others = np.add.reduceat(small, self.first_edge[:-1]) if len(p) else p
        with np.errstate(divide="ignore"):
            self.log_rest = np.where(p > 0.5, np.log(others)[self.at], np.log1p(-np.minimum(p, 0.5)))  # of all else at its start
        upto = np.cumsum(p)
        self.upto = upto - np.concatenate([[0.0], upto])[self.first_edge[self.at]]  # within the edge's start
        self.last = np.zeros(len(p), bool)
        self.last[self.first_edge[1:][np.diff(self.first_edge) > 0] - 1] = True

    def options(self, position: int, without: list[int]) -> list[int]:
        return [e for e in range(self.first_edge[position], self.first_edge[position + 1]) if e not in without]

    def choose(self, position: np.ndarray, u: np.ndarray) -> np.ndarray:
        e = self.first_edge[position]
        on = np.flatnonzero((self.upto[e] < u) & ~self.last[e])
        while len(on):
            e[on] += 1
            x = e[on]
            on = on[(self.upto[x] < u[on]) & ~self.last[x]]
        return e

    def walk(self, position: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Edges of a random path from each position to its chunk's end, in order, and their numbers."""
        live, edges, owners, step = np.arange(len(position)), [], [], 0
        while len(live):
            e = self.choose(position, _uniform(key + _U(step)))
            edges.append(e)
            owners.append(live)
            on = ~self.ends_here[e]
            live, key, position, step = live[on], key[on], self.to[e][on], step + 1
        if not edges:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        owner = np.concatenate(owners)
        order = np.argsort(owner, kind="stable")
        return np.concatenate(edges)[order], np.bincount(owner, minlength=int(owner.max()) + 1)


def _uniform(key: np.ndarray) -> np.ndarray:
    return ((mix(key * _U(0x9E3779B97F4A7C15) + _U(1)) >> _U(11)).astype(np.float64) + 0.5) * 2.0**-53


def _uniform_one(key: int) -> float:
    """``_uniform`` of one key."""
    x = (key * 0x9E3779B97F4A7C15 + 1) & _ALL
    x = ((x ^ (x >> 30)) * 0xBF58476D1CE4E5B9) & _ALL
    x = ((x ^ (x >> 27)) * 0x94D049BB133111EB) & _ALL
    return (((x ^ (x >> 31)) >> 11) + 0.5) * 2.0**-53


def _gumbel(u: np.ndarray) -> np.ndarray:
    return -np.log(-np.log(u))


class Path:
    """A sampled path: its edges, its value, and the bounds of what else could be chosen at each of
    its edges from ``since`` on (there, all but ``without``)."""

    def __init__(self, lattice: Lattice, edges: np.ndarray, value: float, since: int, without: list[int], key: np.uint64):
        self.edges, self.value, self.since, self.without = edges, value, since, without
        log_p = lattice.log_p[edges]
        reach = np.concatenate([[0.0], np.cumsum(log_p)])
        self.log_prob = float(reach[-1])
        other = lattice.log_rest[edges[since:]]
        if len(without) and len(other):
            left = sum(math.exp(lattice.log_p[e]) for e in lattice.options(lattice.at[without[0]], without))
            other[0] = math.log(left) if left else -np.inf
        # as if not truncated: truncation at ``value`` keeps their order
        self.bounds = reach[since:-1] + other + _gumbel(_uniform(key + np.arange(len(other), dtype=_U)))
        self._look()

    def _look(self) -> None:
        self.at = int(np.argmax(self.bounds)) if len(self.bounds) else -1
        free = float(self.bounds[self.at]) if self.at >= 0 else -np.inf
        # the greatest of Gumbel variates that stay below ``value``
        self.best = -float(np.logaddexp(-self.value, -free)) if free > -np.inf else -np.inf

    def take(self) -> tuple[float, int, list[int]]:
        """The best bound, its place, and the edges excluded there; it is then gone from this path."""
        value, place = self.best, self.since + self.at
        without = [*self.without, int(self.edges[place])] if self.at == 0 and self.without else [int(self.edges[place])]
        self.bounds[self.at] = -np.inf
        self._look()
        return value, place, list(dict.fromkeys(without))


def sample_text(lattice: Lattice, chunks: np.ndarray, fresh: list[tuple[np.ndarray, np.ndarray]], key: np.uint64) -> tuple[list[Path], float]:
    """Paths in order of value, as many as ``fresh`` has independent walks (edges, first edge of each
    chunk), and the value after the last."""
    base = int(key)
    draw = lambda n: _uniform_one((base + n) & _ALL)
    edges, _ = fresh[0]
    paths = [Path(lattice, edges, -math.log(-math.log(draw(1))), 0, [], key + _U(1 << 40))]
    while True:
        source = max(paths, key=lambda p: p.best)
        if len(paths) == len(fresh) or np.isneginf(source.best):
            return paths, source.best
        k = len(paths)
        value, place, without = source.take()
        position = lattice.at[source.edges[place]]
        options = lattice.options(position, without)
        share = list(accumulate(math.exp(lattice.log_p[e]) for e in options))
        edge = options[min(len(options) - 1, bisect_right(share, draw(16 * k) * share[-1]))]
        tail, n = [edge], 0
        while not lattice.ends_here[edge]:
            n += 1
            u, edge = draw((k << 20) + n), int(lattice.first_edge[lattice.to[edge]])
            while lattice.upto[edge] < u and not lattice.last[edge]:
                edge += 1
            tail.append(edge)
        chunk = int(np.count_nonzero(lattice.ends_here[source.edges[:place]]))
        walked, first = fresh[k]
        edges = np.concatenate([source.edges[:place], tail, walked[first[chunk + 1] :]]).astype(np.int64)
        paths.append(Path(lattice, edges, value, place, without + [tail[0]], key + _U((k + 1) << 40)))


def sample_slice(pieces: Pieces, ids: list, texts: list[str], k: int, seed: int, smooth: float) -> Iterator[tuple]:
    """(row, sample from 1, ids, log-probability, value, inclusion)."""
    lattice = Lattice(pieces, texts, smooth)
    row_key = mix(np.array([-(2**63) if i is None else i for i in ids], np.int64).view(_U) + mix(np.array([seed], _U)))
    count = np.diff(lattice.first_chunk)
    nth = np.arange(len(lattice.kind)) - np.repeat(lattice.first_chunk[:-1], count)
    start = lattice.origin[lattice.kind]
    walks = []
    for j in range(k):
        key = mix(np.repeat(row_key, count) + nth.astype(_U) * _U(0xD1342543DE82EF95) + _U((j + 1) << 48))
        edges, number = lattice.walk(start, key)
        walks.append((edges, np.concatenate([[0], np.cumsum(number)])))
    for d in range(len(texts)):
        a, b = lattice.first_chunk[d], lattice.first_chunk[d + 1]
        if a == b:
            yield d, 1, np.zeros(0, np.int64), 0.0, 0.0, 1.0
            continue
        fresh = [(edges[first[a] : first[b]], first[a : b + 1] - first[a]) for edges, first in walks]
        paths, threshold = sample_text(lattice, lattice.kind[a:b], fresh, row_key[d])
        for n, path in enumerate(paths):
            inclusion = 1.0 if np.isneginf(threshold) else float(-np.expm1(-np.exp(min(50.0, path.log_prob - threshold))))
            yield d, n + 1, _ids(pieces, lattice.piece[path.edges]), path.log_prob, path.value, inclusion


def _ids(pieces: Pieces, found: np.ndarray) -> np.ndarray:
    if len(found) and found.min() >= 0:
        return found
    plain = (found < 0) & (found >= -128)  # one byte each
    if plain.any():
        found = np.where(plain, pieces.byte_id[np.where(plain, -1 - found, 0)], found)
    if not len(found) or found.min() >= 0:
        return found
    out: list[np.ndarray] = []
    bare = np.flatnonzero(found < 0)
    last = 0
    for at in bare.tolist():
        out += [found[last:at], pieces.byte_id[np.frombuffer(chr(-1 - int(found[at])).encode(), np.uint8)]]
        last = at + 1
    return np.concatenate([*out, found[last:]]) if out else found


def sample_segmentations(df: DataFrame, model_path: str, k: int = 3, seed: int = 7, smooth: float = 1.0, id_col: str = "doc_id", text_col: str = "text", digest: bool = False) -> DataFrame:
    """doc_id, sample (from 1, by value), ids, log_prob, value, inclusion: up to ``k`` distinct
    segmentations of every text. With ``digest``, n_pieces, ids_crc32 (of the ids as little-endian
    32-bit integers) and round_trip (they decode to the text) stand for ids."""
    ship(df.sparkSession)
    tail = "n_pieces long, ids_crc32 long, round_trip boolean" if digest else "ids array<int>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = load(model_path)
        for batch in slices(batches, most=2 << 20):
            ids, texts = batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()
            rows = []
            for d, n, found, log_prob, value, inclusion in sample_slice(pieces, ids, texts, k, seed, smooth):
                more = (len(found), zlib.crc32(found.astype("<u4").tobytes()), pieces.decode(found) == texts[d].encode()) if digest else (found.astype(np.int32),)
                rows.append((ids[d], n, log_prob, value, inclusion, *more))
            kinds = [pa.int64(), pa.int32(), *[pa.float64()] * 3, *([pa.int64(), pa.int64(), pa.bool_()] if digest else [pa.list_(pa.int32())])]
            names = ["doc_id", "sample", "log_prob", "value", "inclusion", *(["n_pieces", "ids_crc32", "round_trip"] if digest else ["ids"])]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names)

    return documents(df, id_col, text_col).mapInArrow(run, f"doc_id long, sample int, log_prob double, value double, inclusion double, {tail}")


def decode(df: DataFrame, model_path: str, ids_col: str = "ids", out_col: str = "text") -> DataFrame:
    """``df`` with the text of its ids (null ids: null); ids out of range raise."""
    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = load(model_path)
        for b in batches:
            out = [None if x is None else pieces.decode(np.array(x, np.int64)).decode("utf-8", "replace") for x in b.column(ids_col).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out, pa.string())], [*b.schema.names, out_col])

    return df.mapInArrow(run, f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in df.schema)}, `{out_col}` string")
