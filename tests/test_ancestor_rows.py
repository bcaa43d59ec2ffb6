"""Exact scores from rows of the source's ancestors; what is found where one machine holds the adjacency."""

import random

import numpy as np
import pytest

from echowalk.functions.rng import draw_local, draws_local
from echowalk.operators import exact, walks
from echowalk.sources import graphs


@pytest.mark.parametrize("n, m, steps, cells", [(30, 70, 1, 1 << 21), (30, 70, 2, 64), (60, 500, 4, 64), (30, 70, 5, 1 << 21), (12, 14, 5, 64)])
def test_single_source_makes_rows_of_ancestors_only(spark, monkeypatch, n, m, steps, cells):
    rng = random.Random(n + m)
    edges = sorted({(rng.randrange(n), rng.randrange(n)) for _ in range(m)} | {(0, 0), (0, 1), (1, 0)})
    g = graphs.from_edges(spark.createDataFrame(edges, "src long, dst long"))
    nodes = sorted({x for e in edges for x in e})
    monkeypatch.setattr(exact, "all_pairs", None)
    monkeypatch.setattr(exact, "CELLS", cells)
    monkeypatch.setattr(exact, "SMALL_SIDE", 0)
    for source in (nodes[0], nodes[-1]):
        want = exact.local_matrix(edges, nodes, 0.6, steps)[nodes.index(source)]
        got = {r["node"]: r["score"] for r in exact.single_source(g, source, 0.6, steps).collect()}
        assert [got.get(v, 0.0) for v in nodes] == pytest.approx(list(want), abs=1e-12)
        assert set(got) == {v for v, x in zip(nodes, want) if x > 0}


@pytest.mark.parametrize("directed", [True, False])
def test_reach_of_one_machine(spark, monkeypatch, directed):
    rng = random.Random(4)
    g = graphs.from_edges(spark.createDataFrame([(rng.randrange(40), rng.randrange(40)) for _ in range(45)], "src long, dst long"), directed=directed)
    adj = walks.prepared(g)
    for source, longest in ((3, 1), (5, 2), (7, 9)):
        ids = spark.createDataFrame([(source,)], "id long")
        here = {tuple(r) for r in walks.reach(g, ids, longest, adj).collect()}
        with monkeypatch.context() as m:
            m.setattr(walks, "LOCAL_EDGES", 0)
            assert here == {tuple(r) for r in walks.reach(g, ids, longest, adj).collect()}
    assert walks.prepared(g) is adj


def test_draws_of_many_keys():
    a, b = np.array([0, 5, 2**40, -3]), np.array([1, 2, 3, 4])
    assert draws_local(42, "step", a, b, 7).tolist() == [draw_local(42, "step", x, y, 7) for x, y in zip(a.tolist(), b.tolist())]
