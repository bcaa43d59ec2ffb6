"""The pipeline's near_dedup stage links by SimHash, row by row."""

import random

import corpus_pipeline as cp

from test_llm import brute_components, brute_fingerprint

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def test_near_stage_links_at_three_bits_with_odd_ids(spark):
    rng, docs = random.Random(11), []
    for k in range(30):
        w = rng.choices([f"w{x}" for x in range(200)], k=rng.randint(80, 400))
        docs.append((rng.choice([None, k % 7, k]), " ".join(w)))
        for _ in range(3):
            w[rng.randrange(len(w))] = f"n{rng.randint(0, 99)}"
            docs.append((rng.choice([None, k % 7, k]), " ".join(w)))
    docs += [(3, None), (None, ""), (3, "a b"), (3, "A  b")]
    fps = [brute_fingerprint(t or "") for _, t in docs]
    of = brute_components(list(range(len(docs))), lambda a, b: (fps[a] ^ fps[b]).bit_count() <= 3)
    least = {}
    for k, (i, _) in enumerate(docs):
        key = (i is None, i or 0)
        least[of[k]] = min(least.get(of[k], key), key)
    want = sorted(least.values())
    df = spark.createDataFrame([(i, t, "en", "s", None) for i, t in docs], SCHEMA).repartition(3)
    got = sorted((r["doc_id"] is None, r["doc_id"] or 0) for r in dict(cp.STAGES)["near_dedup"](spark, df, "").collect())
    assert got == want and len(got) < len(docs) - 10
