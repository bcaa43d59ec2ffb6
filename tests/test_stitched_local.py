"""Stitching gives the same walks and shortfalls where the adjacency is sent to all and where it is not."""

import pytest

from echowalk.functions.sampling import SamplingPlan
from echowalk.operators import stitching, walks
from echowalk.operators.stitching import Supply, stitched
from echowalk.sources import graphs


@pytest.mark.parametrize("rule", [Supply(4, 1.0, 0.0), Supply(4, 1.0, 0.0, True)])
def test_same_walks_by_one_exchange_a_level(spark, monkeypatch, rule):
    edges = [(1, 2), (3, 2), (2, 4), (3, 4), (4, 1), (5, 3)] + [(10 + k, 10 + (k + s) % 7) for k in range(7) for s in (1, 2)] + [(k, 40) for k in range(20, 30)] + [(40, 10)]
    plan, kept, seen = SamplingPlan.create(30, 0.35, 0.3), stitching.keep, []
    monkeypatch.setattr(stitching, "keep", lambda df, label: seen.append(label) or kept(df, label))

    def run():
        g = graphs.from_edges(spark.createDataFrame(edges, "src long, dst long"))
        steps, short = stitched(g, plan, walks.planned(g, plan, 3), walks.prepared(g), 3, rule)
        return sorted(map(tuple, steps.collect())), sorted(map(tuple, short.collect()))

    got, labels = run(), list(seen)
    seen.clear()
    monkeypatch.setattr(walks, "LOCAL_EDGES", 1)
    assert got == run() and len(got[0]) > 500 and (rule.slack > 1 or rule.reuse or sum(m for _, m in got[1]))
    assert "segments" not in labels and "segments" in seen
