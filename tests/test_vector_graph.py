"""The vector graph by blocks equals all pairs one by one."""

import math
import random

import pytest

from echowalk.sources import workloads


@pytest.mark.parametrize("block", [4096, 7])
def test_blocks_give_the_nearest_of_all(spark, tmp_path, monkeypatch, block):
    rng = random.Random(2)
    vecs = [[float(rng.randint(-2, 2)) for _ in range(3)] for _ in range(40)]
    vecs = [x if any(x) else [1.0, 0.0, 0.0] for x in vecs] + [[1.0, 1.0, 0.0]] * 9 + [[0.0, 0.0, 0.0]]
    rows = list(enumerate(vecs))
    rng.shuffle(rows)
    spark.createDataFrame([(i, x, 0) for i, x in rows], "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")

    def cosine(a, b):
        size = math.sqrt(sum(x * x for x in a)) * math.sqrt(sum(x * x for x in b))
        return round(sum(x * y for x, y in zip(a, b)) / size, 9) if size else None

    want = set()
    for i, a in rows:
        if any(a):
            want |= {(i, j) for _, j in sorted((-cosine(a, b), j) for j, b in rows if j != i and any(b))[:2]}
    real, seen = workloads._close, []
    monkeypatch.setattr(workloads, "_close", lambda k: seen.append(k) or real(k))
    got = {tuple(r) for r in workloads.embedding_knn(spark, str(tmp_path), 2, block=block).edges.collect()}
    zero = len(rows) - 1
    assert {e for e in got if e[0] != zero} == want and seen == [2]
    assert sum(e[0] == zero for e in got) == 2
