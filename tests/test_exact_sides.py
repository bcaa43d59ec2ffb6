"""Exact scores of one source without pairs of the larger side."""

import random

import pytest

from echowalk.operators import exact
from echowalk.sources import graphs


@pytest.mark.parametrize("directed", [True, False])
def test_single_source_makes_no_pairs_of_the_larger_side(spark, directed, monkeypatch):
    rng = random.Random(8)
    pairs = sorted({(2 * rng.randrange(40), 2 * rng.randrange(7) + 1) for _ in range(110)} | {(500, 501)})
    g = graphs.from_edges(spark.createDataFrame(pairs, "src long, dst long"), directed=directed)
    edges = pairs if directed else pairs + [(b, a) for a, b in pairs]
    nodes = sorted({x for e in edges for x in e})
    monkeypatch.setattr(exact, "all_pairs", None)
    for source, steps in ((1, 4), (1, 5), (pairs[0][0], 3), (pairs[0][0], 4)):
        want = exact.local_matrix(edges, nodes, 0.6, steps)[nodes.index(source)]
        got = {r["node"]: r["score"] for r in exact.single_source(g, source, 0.6, steps).collect()}
        assert [got.get(v, 0.0) for v in nodes] == pytest.approx(list(want), abs=1e-12)
        assert set(got) == {v for v, x in zip(nodes, want) if x > 0}


def test_what_does_not_depend_on_c_is_made_once(spark, monkeypatch):
    pairs = [(2 * k, 2 * (k * j % 5) + 1) for k in range(12) for j in (1, 3)]
    g = graphs.from_edges(spark.createDataFrame(pairs, "src long, dst long"), directed=False)
    edges = sorted(set(pairs)) + sorted({(b, a) for a, b in pairs})
    nodes, kept, seen = sorted({x for e in edges for x in e}), exact.keep, []
    monkeypatch.setattr(exact, "keep", lambda df, label: seen.append(label) or kept(df, label))
    for c in (0.6, 0.4):
        want = exact.local_matrix(edges, nodes, c, 5)[nodes.index(1)]
        got = {r["node"]: r["score"] for r in exact.single_source(g, 1, c, 5).collect()}
        assert [got.get(v, 0.0) for v in nodes] == pytest.approx(list(want), abs=1e-12)
    assert seen == ["sides", "middle"]
