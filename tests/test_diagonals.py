"""Exact scores of one source by diagonals and places of its ancestors' walks, where the graph is too large for its rows."""

import random

import pytest

from echowalk.operators import exact
from echowalk.sources import graphs


@pytest.mark.parametrize("n, m, steps, cells, task_edges, limit", [(30, 70, 1, 64, 100, "MOST_EDGES"), (40, 200, 4, 64, 1000, "MOST_CELLS"), (30, 60, 4, 1 << 21, 1000, "MOST_EDGES"), (30, 60, 4, 64, 0, "MOST_EDGES")])
def test_single_source_makes_no_pairs_beyond_walks_of_ancestors(spark, monkeypatch, n, m, steps, cells, task_edges, limit):
    rng = random.Random(n + m)
    edges = sorted({(rng.randrange(n), rng.randrange(n)) for _ in range(m)} | {(0, 0), (0, 1), (1, 0), (n, 0)})
    g = graphs.from_edges(spark.createDataFrame(edges, "src long, dst long"))
    nodes = sorted({x for e in edges for x in e})
    monkeypatch.setattr(exact, "all_pairs", None)
    monkeypatch.setattr(exact, limit, 0)
    monkeypatch.setattr(exact, "SMALL_SIDE", 0)
    monkeypatch.setattr(exact, "CELLS", cells)
    monkeypatch.setattr(exact, "TASK_EDGES", task_edges)
    for source in (nodes[0], n):  # the last has no in-neighbours
        want = exact.local_matrix(edges, nodes, 0.6, steps)[nodes.index(source)]
        got = {r["node"]: r["score"] for r in exact.single_source(g, source, 0.6, steps).collect()}
        assert [got.get(v, 0.0) for v in nodes] == pytest.approx(list(want), abs=1e-12)
        assert set(got) == {v for v, x in zip(nodes, want) if x > 0}
