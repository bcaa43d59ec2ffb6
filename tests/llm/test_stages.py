"""The pipeline's deduplication stages: brute force, repeated rows and null ids."""

import random

import corpus_pipeline as cp

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def frame(spark, docs):
    return spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t)) for i, t in docs], SCHEMA).repartition(3)


def stage(name):
    return dict(cp.STAGES)[name]


def shingles(text):
    w = (text or "").lower().split()
    return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()


def near_kept(docs):
    sets = [shingles(t) for _, t in docs]
    root = list(range(len(docs)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(docs)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if 5 * both >= 4 * (len(sets[a]) + len(sets[b]) - both):
                root[find(a)] = find(b)
    groups = {}
    for k, (i, _) in enumerate(docs):
        groups.setdefault(find(k), []).append(i)
    order = lambda i: (i is None, i or 0)
    return sorted((min(g, key=order) for g in groups.values()), key=order)


def near_docs():
    rng = random.Random(3)
    docs = []
    for _ in range(12):
        w = rng.choices([f"w{k}" for k in range(400)], k=rng.randint(60, 160))
        for _ in range(6):
            docs.append((len(docs), " ".join(w)))
            w = [*w]
            for at in rng.sample(range(len(w)), rng.randint(1, 4)):
                w[at] = f"n{rng.randint(0, 999)}"
    return docs + [(200, "A b c"), (201, "a  b c"), (202, "a b d"), (203, None), (204, "")]


def test_near_stage_joins_from_jaccard_08(spark):
    docs = near_docs()
    got = [r["doc_id"] for r in stage("near_dedup")(spark, frame(spark, docs), "").collect()]
    assert sorted(got) == near_kept(docs) and len(got) < len(docs) - 20


def test_near_links_in_blocks(spark):
    from echowalk.llm import near_dedup

    docs = near_docs()
    got = [r["doc_id"] for r in near_dedup.keep_representatives(frame(spark, docs), block=2).collect()]
    assert sorted(got) == near_kept(docs)


def test_near_links_of_a_crowded_bucket(spark):
    from echowalk.llm import near_dedup

    rng, docs = random.Random(5), []
    base = [f"b{k}" for k in range(120)]
    for _ in range(90):  # about half within 0.8 of each other, all with words in common
        w = [*base]
        for at in rng.sample(range(120), rng.randint(0, 3)):
            w[at] = f"n{rng.randint(0, 99)}"
        docs.append((len(docs), " ".join(w)))
    for block in (4, 16):
        got = [r["doc_id"] for r in near_dedup.keep_representatives(frame(spark, docs), block=block).collect()]
        assert sorted(got) == near_kept(docs)


PASSAGE = " ".join(f"p{k}" for k in range(40))
ROWS = [
    (1, "same text here"), (1, "same text here"), (1, "another text"), (None, "same  text here"), (None, "null id"), (None, "null id"), (None, "alone"),
    (2, None), (None, ""), (5, f"x y {PASSAGE} z"), (None, f"a b {PASSAGE} c"), (None, f"d e {PASSAGE} f"), (5, f"g {PASSAGE}"), (5, f"g {PASSAGE}"),
]


def of(spark, name, docs):
    return sorted(((r["doc_id"], r["text"]) for r in stage(name)(spark, frame(spark, docs), "").collect()), key=repr)


def test_exact_stage_keeps_one_row_of_each_content(spark):
    # of equal contents the longest text stays, then the least id; null ids come last
    want = [(None, "same  text here"), (1, "another text"), (None, "null id"), (None, "alone"), (2, None), *ROWS[9:13]]
    assert of(spark, "exact_dedup", ROWS) == sorted(want, key=repr)


def test_near_stage_decides_by_rows(spark):
    want = [(1, "same text here"), (1, "another text"), (None, "null id"), (None, "alone"), (2, None), (5, f"g {PASSAGE}")]
    docs = [*ROWS[:9], *ROWS[12:], (None, f"g {PASSAGE} h"), (None, f"G {PASSAGE}")]
    assert of(spark, "near_dedup", docs) == sorted(want, key=repr)


def test_substring_stage_decides_by_rows(spark):
    left = ["x y z", "a b c", "d e f", "", ""]  # the last two repeat each other as a whole
    want = [*ROWS[:9], *((i, t) for (i, _), t in zip(ROWS[9:], left))]
    assert of(spark, "substring_dedup", ROWS) == sorted(want, key=repr)
