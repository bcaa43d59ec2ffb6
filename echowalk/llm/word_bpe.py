"""Token ids of a word-level BPE vocabulary file, by a vectorised merge loop.

Equal to ``tokenizers`` for such files (NFC, lower case, white space dropped, a
word-end mark on the last symbol). Texts are cut into words, digits and runs of
signs in arrays of bytes, equal ones are told by comparing them, and the
ids of each distinct one are found once; those of a batch that are new are merged
together, one merge a word and round, in arrays. Chunks with characters beyond the
basic Latin ranges, with the strings of special tokens or with very long
words go through the library itself.
"""

from __future__ import annotations

import gc
import json
import os
import re
import unicodedata
from functools import lru_cache
from itertools import repeat

import numpy as np
import pyarrow as pa

from .common import distinct, packed

_ASCII = re.compile(rb"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^\x09-\x0d\x20a-z0-9]+")
_NONE = np.uint16(65535)  # no merge
_FILL = np.uint16(65535)  # no symbol
_BLOCK = 1 << 18


class PairTable:
    """Ranks of pairs of ids under 2**16, looked up by two hashes."""

    def __init__(self, pairs: np.ndarray, ranks: np.ndarray, bits: int = 20):
        self.shift = np.uint32(32 - bits)
        for k in range(1, 1000):
            self.by = [np.uint32((0x9E3779B1 * (2 * k + 1)) & 0xFFFFFFFF | 1), np.uint32((0x85EBCA77 * (2 * k + 1)) & 0xFFFFFFFF | 1)]
            self.keys, self.ranks = [], []
            left, ranks_left = pairs, ranks
            for by in self.by:
                key, rank = np.full(1 << bits, 0xFFFFFFFF, np.uint32), np.full(1 << bits, _NONE, np.uint16)
                slot, first = np.unique((left * by) >> self.shift, return_index=True)
                key[slot], rank[slot] = left[first], ranks_left[first]
                rest = np.ones(len(left), bool)
                rest[first] = False
                left, ranks_left = left[rest], ranks_left[rest]
                self.keys.append(key)
                self.ranks.append(rank)
            if not len(left):
                return
        raise ValueError("no collision-free hashes found")

    def rank(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        pair = (a.astype(np.uint32) << np.uint32(16)) | b.astype(np.uint32)
        s0, s1 = (pair * self.by[0]) >> self.shift, (pair * self.by[1]) >> self.shift
        return np.where(self.keys[0][s0] == pair, self.ranks[0][s0], np.where(self.keys[1][s1] == pair, self.ranks[1][s1], _NONE))


#: Kinds of bytes: white space, letters, digits, all other signs, and bytes that need a closer look.
_BLANK, _LETTER, _DIGIT, _SIGN, _ODD = range(5)


def _kinds() -> tuple[np.ndarray, np.ndarray]:
    """Kind of every byte, and A-Z as a-z."""
    kind, lower = np.full(256, _SIGN, np.uint8), np.arange(256, dtype=np.uint8)
    kind[[9, 10, 11, 12, 13, 32]] = _BLANK
    kind[ord("0") : ord("9") + 1] = _DIGIT
    for first in b"aA":
        kind[first : first + 26] = _LETTER
    kind[ord("'")] = kind[128:] = _ODD
    lower[ord("A") : ord("Z") + 1] += 32
    return kind, lower


_KIND, _LOWER = _kinds()


def units(data: np.ndarray, off: np.ndarray) -> tuple[pa.LargeBinaryArray, np.ndarray, np.ndarray]:
    """What texts (UTF-8 bytes and offsets) are cut into before merging, without white space, the
    first unit of each text, and the places of units that are chunks as they are. A unit is a lower-case word, a digit or a run of signs; a
    chunk with an apostrophe, a mark of special tokens or characters beyond ASCII and the letters of
    Latin-1 is one unit as it is."""
    kind = _KIND[data]
    # two-byte letters of Latin-1: 0xC3 and a byte from 0x80 on, without the signs of times and division
    lead = np.flatnonzero((data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] != 0x97) & (data[1:] != 0xB7))
    kind[lead] = kind[lead + 1] = _LETTER
    special = np.flatnonzero((data[:-1] == ord("<")) & (data[1:] == ord("|")))
    kind[special] = _ODD
    blank = kind == _BLANK
    opens = np.ones(len(data), bool)
    opens[1:] = blank[:-1]
    opens[off[:-1][np.diff(off) > 0]] = True
    chunk = np.flatnonzero(opens & ~blank)
    odd = np.flatnonzero(kind == _ODD)
    odd = distinct(np.searchsorted(chunk, odd, "right") - 1)
    begin = np.ones(len(data), bool)
    begin[1:] = (kind[1:] != kind[:-1]) | (kind[1:] == _DIGIT)
    begin[chunk] = True
    begin &= ~blank
    small = _LOWER[data]
    small[lead[(data[lead + 1] >= 0x80) & (data[lead + 1] <= 0x9E)] + 1] += 32
    if len(odd):
        last = np.append(chunk[1:], len(data))  # white space behind a chunk does not matter
        inside = np.zeros(len(data) + 1, np.int8)
        inside[chunk[odd]] += 1
        np.subtract.at(inside, last[odd], 1)
        inside = np.cumsum(inside[:-1], dtype=np.int8) > 0
        begin &= ~inside
        begin[chunk[odd]] = True
        small[inside] = data[inside]
    keep = ~blank
    place = np.cumsum(keep) - 1
    start = np.flatnonzero(begin)
    own = small[keep]
    offsets = np.append(place[start], len(own)).astype(np.int64)
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(start), [None, pa.py_buffer(offsets), pa.py_buffer(own)]), np.searchsorted(start, off), np.searchsorted(start, chunk[odd])


class WordBpe:
    """``most``: distinct units kept; beyond it they are forgotten and found anew. Words of over
    ``long`` bytes go through the library, whose time is near-linear in a word's length."""

    def __init__(self, path: str, most: int = 200_000, long: int = 256):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as file:
            model = json.load(file)["model"]
        vocab, self.most, self.long = model["vocab"], most, long
        self._forget()
        if len(vocab) > 65_000:
            raise ValueError("ids must fit 16 bits")
        merges = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        pairs = np.array([vocab[a] << 16 | vocab[b] for a, b in merges], np.uint32)
        self.pairs = PairTable(pairs, np.arange(len(pairs), dtype=np.uint16))
        self.made = np.array([vocab[a + b] for a, b in merges], np.uint16)
        sign = self._byte_signs()
        self.inner = np.array([vocab[sign[b]] for b in range(256)], np.uint16)
        self.last = np.array([vocab[sign[b] + model["end_of_word_suffix"]] for b in range(256)], np.uint16)

    @staticmethod
    def _byte_signs() -> list[str]:
        """The printable stand-in of every byte in byte-level vocabularies: itself if printable in
        Latin-1, else the next code point from 256 on."""
        printable = {*range(33, 127), *range(161, 173), *range(174, 256)}
        spare = iter(range(256, 512))
        return [chr(b if b in printable else next(spare)) for b in range(256)]

    def _forget(self) -> None:
        self.known: dict[bytes, int] = {}  # place of a unit
        self.flat, self.upto = np.zeros(0, "<u4"), np.zeros(1, np.int64)  # all ids in a row, and where each unit's are

    def texts(self, texts: list[bytes]) -> list[bytes]:
        """The ids of each text as little-endian unsigned 32-bit integers."""
        ids, off = self.encode(pa.array(texts, pa.large_binary()))
        return [ids[a:b].tobytes() for a, b in zip(off, off[1:])]

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts in a row, and the offsets of each text's."""
        collecting = gc.isenabled()
        gc.disable()  # all that is made here is without cycles, and much of it
        try:
            return self._encode(texts)
        finally:
            if collecting:
                gc.enable()

    def _encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        found, first, odd = units(*packed(texts))
        coded = found.dictionary_encode()
        kind = np.asarray(coded.indices)
        whole = np.zeros(len(coded.dictionary), bool)
        whole[kind[odd]] = True
        place = self._places(coded.dictionary.to_pylist(), whole)[kind]
        count = np.diff(self.upto)[place]
        end = np.cumsum(count)
        at = np.repeat(self.upto[place] - (end - count), count) + np.arange(int(count.sum()))
        return self.flat[at], np.concatenate([[0], end])[first]

    def _places(self, distinct: list[bytes], whole: np.ndarray) -> np.ndarray:
        """Where the ids of each unit are; ``whole``: which of them are chunks that are yet to be cut."""
        place = np.fromiter(map(self.known.get, distinct, repeat(-1)), np.int64, len(distinct))
        new = np.flatnonzero(place < 0)
        if not len(new):
            return place
        if len(self.known) + len(new) > self.most:
            self._forget()
            new = np.arange(len(distinct))
        base, got = len(self.known), []
        for at in range(0, len(new), 50_000):
            some = new[at : at + 50_000].tolist()
            got += self._learn([distinct[k] for k in some], whole[some].tolist())
        place[new] = np.arange(base, base + len(new))
        self.known.update(zip([distinct[k] for k in new.tolist()], range(base, base + len(new))))
        self.flat = np.concatenate([self.flat, np.frombuffer(b"".join(got), "<u4")])
        self.upto = np.concatenate([self.upto, self.upto[-1] + np.cumsum([len(f) // 4 for f in got])])
        return place

    def _learn(self, distinct: list[bytes], whole: list[bool]) -> list[bytes]:
        words: list[bytes] = []
        spans, by_library = [], []
        for unit, uncut in zip(distinct, whole):
            parts = self._words(unit) if uncut else [unit]
            if parts is None or (len(unit) > self.long and max(map(len, parts), default=0) > self.long):
                by_library.append(unit)
                spans.append(None)
            else:
                spans.append((len(words), len(words) + len(parts)))
                words += parts
        ids = self._merge(words)
        others = iter(self.library.encode_batch_fast([c.decode() for c in by_library], add_special_tokens=False) if by_library else ())
        return [np.array(next(others).ids, "<u4").tobytes() if span is None else ids[span[0]] if span[1] == span[0] + 1 else b"".join(ids[slice(*span)]) for span in spans]

    @staticmethod
    def _words(chunk: bytes) -> list[bytes] | None:
        if b"<|" in chunk:
            return None
        if chunk.isascii():
            return _ASCII.findall(chunk.lower())
        text = chunk.decode()
        if max(text) > "ſ" or "İ" in text:
            return None
        return [w.encode() for w in _letters().findall(unicodedata.normalize("NFC", text).lower())]

    def _merge(self, words: list[bytes]) -> list[bytes]:
        out: list[bytes] = [b""] * len(words)
        sizes = np.array([len(w) for w in words], np.int64)
        order = np.argsort(sizes, kind="stable")
        sizes = sizes[order]
        at = int(np.searchsorted(sizes, 1))
        while at < len(words):
            to = int(np.searchsorted(sizes, sizes[at] + sizes[at] // 8, "right"))
            to = min(to, at + max(1, _BLOCK // int(sizes[at])))
            self._merge_alike(order[at:to], words, int(sizes[to - 1]), out)
            at = to
        return out

    def _merge_alike(self, which: np.ndarray, words: list[bytes], width: int, out: list[bytes]) -> None:
        """Words of about the same length as rows of a matrix of ids, filled up behind."""
        own = [words[k] for k in which]
        length = np.array([len(w) for w in own])
        raw = np.frombuffer(b"".join([w.ljust(width, b"\0") for w in own]), np.uint8).reshape(-1, width)
        ids = self.inner[raw]
        row = np.arange(len(ids))
        ids[row, length - 1] = self.last[raw[row, length - 1]]
        ids[np.arange(width) >= length[:, None]] = _FILL
        rank = np.full(ids.shape, _NONE, np.uint16)
        rank[:, :-1] = self.pairs.rank(ids[:, :-1], ids[:, 1:])
        column = np.arange(width, dtype=np.int32)
        while True:
            at = rank.argmin(1)
            least = rank[row, at]
            done = least == _NONE
            if done.any():
                self._give(which[done], ids[done], out)
                left = ~done
                ids, rank, at, least, which = ids[left], rank[left], at[left], least[left], which[left]
                if not len(ids):
                    return
                row = np.arange(len(ids))
            ids[row, at] = self.made[least]
            behind = column[:-1] > at[:, None]
            np.copyto(ids[:, :-1], ids[:, 1:].copy(), where=behind)
            np.copyto(rank[:, :-1], rank[:, 1:].copy(), where=behind)
            ids[:, -1], rank[:, -1] = np.where(at == width - 1, ids[:, -1], _FILL), _NONE
            follows = np.minimum(at + 1, width - 1)
            rank[row, at] = np.where(at + 1 < width, self.pairs.rank(ids[row, at], ids[row, follows]), _NONE)
            ahead = np.flatnonzero(at)
            rank[ahead, at[ahead] - 1] = self.pairs.rank(ids[ahead, at[ahead] - 1], ids[ahead, at[ahead]])

    @staticmethod
    def _give(which: np.ndarray, ids: np.ndarray, out: list[bytes]) -> None:
        true = ids != _FILL
        flat = ids[true].astype("<u4").tobytes()
        end = 4 * np.cumsum(true.sum(1))
        start = 0
        for k, e in zip(which.tolist(), end.tolist()):
            out[k] = flat[start:e]
            start = e


@lru_cache(1)
def _letters():
    import regex

    return regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+")


@lru_cache(2)
def load(path: str) -> WordBpe:
    return WordBpe(path)
