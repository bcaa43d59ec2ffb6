"""Walks that cannot meet the source's are not walked; nothing else changes."""

import random

import pytest

from echowalk.functions.sampling import SamplingPlan
from echowalk.operators import meeting, walks
from echowalk.plans import catalogue, simrank
from echowalk.sources import graphs, workloads


def reachable(edges, source, longest):
    """Nodes with a walk of k steps to where a walk of k steps of the source ends, for some k."""
    nbrs = {}
    for a, b in edges:
        nbrs.setdefault(b, set()).add(a)
    nodes = {x for e in edges for x in e}
    at, out = {v: {v} for v in nodes}, {source}
    for _ in range(longest):
        at = {v: {y for x in s for y in nbrs.get(x, ())} for v, s in at.items()}
        out |= {v for v in nodes if at[v] & at[source]}
    return out


@pytest.mark.parametrize("directed", [True, False])
def test_starts_hold_all_that_can_meet(spark, directed):
    rng = random.Random(4)
    pairs = [(2 * rng.randrange(12), 2 * rng.randrange(12) + 1) for _ in range(14)] + [(100, 101), (102, 101), (200, 200), (201, 200)]
    g = graphs.from_edges(spark.createDataFrame(pairs, "src long, dst long"), directed=directed)
    edges = [tuple(r) for r in g.edges.collect()]
    for source in (pairs[0][1], 101, 200):
        got = {r["id"] for r in simrank.starts_of(g, [source], 6, walks.prepared(g)).collect()}
        assert reachable(edges, source, 6) <= got
        assert len(got) < g.size()


def test_pages_are_not_walked_for_a_target(spark, sf):
    g = workloads.page_links(spark, sf, directed=False)
    plan = SamplingPlan.create(g.size(), 0.6, 0.2)
    some = catalogue._meeting_tuples(g, plan)
    assert some.filter("start % 2 = 0").isEmpty() and not some.filter("start != 1").isEmpty()
    every = simrank.labelled_tuples(g, plan, 42, "local")
    for once in (True, False):
        want = sorted(map(tuple, meeting.by_join(every, 1, once).collect()))
        assert want and sorted(map(tuple, meeting.by_join(some, 1, once).collect())) == want


def test_large_adjacencies_are_walked_stepwise(spark, sf, monkeypatch):
    g = workloads.page_links(spark, sf, directed=False)
    starts = g.nodes.filter("id < 20").select("id")
    plan = SamplingPlan.create(g.size(), 0.6, 0.3)
    want = sorted(map(tuple, walks.generate(g, plan, 42, "local", starts=starts).collect()))
    monkeypatch.setattr(walks, "LOCAL_EDGES", 10)
    monkeypatch.setattr(walks, "local", None)
    assert sorted(map(tuple, walks.generate(g, plan, 42, "local", starts=starts).collect())) == want
