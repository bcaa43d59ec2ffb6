"""Sweeps in rounds against best-fit decreasing one piece at a time; token ids of long words."""

import collections
import random
import time

import numpy as np
import public_tokenizers
import pytest

from echowalk.llm import packing, word_bpe

BPE = public_tokenizers.path("word_bpe_49k.json")


def best_fit_decreasing(lengths, capacity):
    return packing.plan_classes(dict(collections.Counter(lengths)), capacity)[1]


def packed(spark, lengths, capacity, rows_a_task):
    rows = [(i, 0, 0, n, i) for i, n in enumerate(lengths)]
    df = spark.createDataFrame(rows, "doc_id long, piece int, start long, length int, ids_crc32 long")
    out = packing.place(df, capacity, rows_a_task).collect()
    assert sorted((r["doc_id"], r["length"]) for r in out) == list(enumerate(lengths))
    by = collections.defaultdict(list)
    for r in out:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for parts in by.values():
        end = 0
        for offset, length in sorted(parts):
            assert offset == end
            end += length
        assert end <= capacity
    return len(by)


@pytest.mark.parametrize("rows_a_task", [10**6, 60])
def test_rounds_against_best_fit_decreasing(spark, rows_a_task):
    rng = random.Random(11)
    mixed = [min(300, int(rng.lognormvariate(3.6, 1)) + 1) for _ in range(700)]
    assert packed(spark, mixed, 300, rows_a_task) <= best_fit_decreasing(mixed, 300) + 2
    alike = [rng.randint(88, 160) for _ in range(300)]  # two or three a sequence
    assert packed(spark, alike, 300, rows_a_task) <= best_fit_decreasing(alike, 300)


def test_rows_that_repeat_and_extremes(spark):
    for lengths, want in (([7] * 50, 25), ([16] * 3 + [1] * 16, 4), ([], 0), ([16], 1), ([9, 9, 7, 7], 2)):
        assert packed(spark, lengths, 16, 8) == want


def test_sweep_is_best_fit():
    # falling sizes: gap 9, piece 8, piece 7, gap 6, gap 5, piece 5, piece 1
    hits, gaps, waits, left, changed = packing.sweep(np.array([0, 1, 1, 0, 0, 1, 1]), np.array([9, 8, 7, 6, 5, 5, 1]))
    assert (hits, gaps, waits, left, changed) == ([1, 5, 6], [0, 4, 0], [2], [(6, 3)], {0, 4})
    rng = random.Random(12)
    for _ in range(100):
        tokens = sorted(((rng.randint(1, 30), rng.randint(0, 1)) for _ in range(40)), key=lambda t: (-t[0], t[1]))
        room, want, waiting = {}, [], []
        for at, (n, k) in enumerate(tokens):
            if k == 0:
                room[at] = n
            elif fits := [(r, -g) for g, r in room.items() if r >= n]:
                want.append((at, min(fits)[0]))
                room[-min(fits)[1]] -= n
            else:
                waiting.append(at)
        hits, gaps, waits, left, _ = packing.sweep(np.array([k for _, k in tokens]), np.array([n for n, _ in tokens]))
        assert hits == [at for at, _ in want] and waits == waiting
        assert sorted(n for n, _ in left) == sorted(r for r in room.values() if r)


def test_carries_pair_ranks_once_and_downwards():
    rng = random.Random(13)
    for _ in range(200):
        waits, free = ([rng.randint(0, 6) for _ in range(5)] for _ in range(2))
        k = rng.randint(1, 3)
        pieces, gaps = [], []
        for q, rank, i, last, n, each in packing.carries(waits, free, lambda task, before: k):
            assert i < q and each == k
            pieces += [(q, rank + x) for x in range(n)]
            gaps += [(i, last - x) for x in range(-(-n // k))]
        assert len(set(pieces)) == len(pieces) and all(r < waits[q] for q, r in pieces)
        assert len(set(gaps)) == len(gaps) and all(0 <= r < free[i] for i, r in gaps)


def test_long_words_take_linear_time():
    from tokenizers import Tokenizer

    library, own = Tokenizer.from_file(BPE), word_bpe.WordBpe(BPE)
    texts = ["ab" * 3000, "x" * 257 + " " + "é" * 300, "A1" * 400 + "'s" * 300, "!" * 999]
    for text, ids in zip(texts, own.texts([t.encode() for t in texts])):
        assert np.frombuffer(ids, "<u4").tolist() == library.encode(text, add_special_tokens=False).ids
    began = time.time()
    own.texts(["qz".encode() * 1_000_000])
    assert time.time() - began < 20


def test_units_of_odd_texts_equal_the_library():
    from tokenizers import Tokenizer

    library, own = Tokenizer.from_file(BPE), word_bpe.WordBpe(BPE, most=60)
    rng = random.Random(13)
    signs = "aAbBzZ09 '’.,;<|>-\t\néÉßÀ×÷ÿÞ ſİ日x́\x1c\x85\xa0ĀÆæ"
    texts = ["<|endoftext|>x <|ENDOFTEXT|> y", "don't l'été ''s", "÷a×b", *("".join(rng.choices(signs, k=rng.randint(0, 60))) for _ in range(600))]
    for at in range(0, len(texts), 100):
        for text, ids in zip(texts[at : at + 100], own.texts([t.encode() for t in texts[at : at + 100]])):
            assert np.frombuffer(ids, "<u4").tolist() == library.encode(text, add_special_tokens=False).ids


def test_rows_of_one_task_are_not_dealt(spark, monkeypatch):
    def dealt(*_):
        raise AssertionError("rows that one task holds went through an exchange")

    kind = type(spark.range(0))
    monkeypatch.setattr(kind, "repartition", dealt)
    monkeypatch.setattr(kind, "repartitionByRange", dealt)
    lengths = [16] * 3 + [9, 9, 7, 7] + [3] * 10
    assert packed(spark, lengths, 16, 100) <= best_fit_decreasing(lengths, 16)
