"""Equality of words, windows and chunks where structured texts break weak hashes."""

import itertools
import math
import random

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
import sentencepiece

from echowalk.llm import segmentation, substring_dedup
from echowalk.llm.common import SpanHash, Words, byte_table, word_hashes

PIECES = public_tokenizers.path("piece_bpe_32k.model")


def thue_morse(n, a="a", b="b"):
    return "".join(b if k.bit_count() % 2 else a for k in range(n))


@pytest.mark.parametrize("letters", [1024, 2048])
def test_long_words_that_weak_hashes_confuse(spark, letters):
    one, two = thue_morse(letters), thue_morse(letters, "b", "a")
    rest = " ".join(f"w{k}" for k in range(34))
    docs = [(1, f"{one} {rest}"), (2, f"{two} {rest}"), (3, f"{one} x {rest}"), (4, f"{one} {rest}")]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = {r["doc_id"]: r["n_removed"] for r in substring_dedup.remove_repeats(df, window=35).collect()}
    assert got == {1: 35, 2: 0, 3: 0, 4: 35}
    for order in ((one, two), (two, one)):
        p = segmentation.load(PIECES)
        for d, _, ids, *_ in segmentation.sample_slice(p, [1, 2], list(order), 2, 7, 1.0):
            assert p.decode(ids).decode() == order[d]


def test_windows_of_words_in_a_structured_order(spark):
    a, b = thue_morse(64).replace("a", "a ").replace("b", "b "), thue_morse(64, "b", "a").replace("a", "a ").replace("b", "b ")
    df = spark.createDataFrame([(1, a), (2, b)], "doc_id long, text string")
    got = {r["doc_id"]: r["n_removed"] for r in substring_dedup.remove_repeats(df, window=64, gram=6).collect()}
    assert got == {1: 0, 2: 0}


def test_span_hashes_tell_runs_apart():
    rng = random.Random(3)
    texts = [" ".join(rng.choices(["a", "b", "ab", "ba", "c" * 70, "c" * 71, "c" * 70 + "d"], k=rng.randint(0, 40))) for _ in range(300)]
    w = Words(pa.array(texts, pa.large_string()), byte_table())
    h = [SpanHash(word_hashes(w, key), key) for key in (0, 1)]
    every = list(itertools.chain.from_iterable(t.split() for t in texts))
    for spans in h:
        seen = {}
        for n in (1, 2, 5):
            first = np.arange(len(every) - n + 1)
            for s, x in zip(first.tolist(), spans.of(first, first + n - 1).tolist()):
                assert seen.setdefault(x, every[s : s + n]) == every[s : s + n]
        assert len(set(spans.of(np.arange(len(every)), np.arange(len(every))).tolist())) == len(set(every))


def every_segmentation(text, model, weight):
    if not text:
        yield ()
    for n in range(1, len(text) + 1):
        i = model.piece_to_id(text[:n])
        if i in weight and model.id_to_piece(i) == text[:n]:
            yield from ((i, *rest) for rest in every_segmentation(text[n:], model, weight))


def test_no_segmentation_is_lost():
    p, m = segmentation.load(PIECES), sentencepiece.SentencePieceProcessor(model_file=PIECES)
    weight = dict(zip(p.id.tolist(), p.weight.tolist()))
    texts = [":=", "ab", "the", "  ", "))", "ing", "==", "''"]
    pieces = [m.id_to_piece(i) for i in sorted(weight)]
    texts += [t[1:] for t in pieces if t.startswith("▁") and 2 <= len(t) <= 4 and "▁" not in t[1:]]
    of = dict(enumerate(texts))
    got = {}
    for d, k, ids, log_p, _, q in segmentation.sample_slice(p, list(of), list(of.values()), 12, 7, 1.0):
        got.setdefault(d, {})[tuple(ids.tolist())] = (log_p, q)
    for d, text in of.items():
        want = set(every_segmentation("▁" + text.replace(" ", "▁"), m, weight))
        assert len(got[d]) == min(12, len(want)) and set(got[d]) <= want, text
        if len(want) <= 12:
            assert all(q == 1.0 for _, q in got[d].values())
            total = sum(math.exp(sum(weight[i] for i in s)) for s in want)
            assert all(abs(v[0] - sum(weight[i] for i in s) + math.log(total)) < 1e-6 for s, v in got[d].items())
    assert len(got[0]) >= 3
