"""Unmet requests of stitching are finished by the same draws with and without exchanges."""

from echowalk.operators import stitching, walks
from echowalk.sources import graphs


def test_finished_without_an_exchange_a_step(spark, monkeypatch):
    edges = [(1, 2), (3, 2), (2, 4), (3, 4), (4, 1), (5, 3)] + [(10 + k, 10 + (k + 1) % 7) for k in range(7)]
    g = graphs.from_edges(spark.createDataFrame(edges, "src long, dst long"))
    adj = walks.prepared(g)
    degree = walks._with_degree(g, None).selectExpr("start AS node", "deg")
    unmet = spark.createDataFrame([(f"{v}/{k}", v, k, [7] * (k % 3), v) for v in (1, 2, 3, 4, 5, 10, 12) for k in range(6)] + [("x/1", 1, 1, [3, 5], None)], "rid string, origin long, own_no int, path array<long>, at long")
    kept, seen = stitching.keep, []
    monkeypatch.setattr(stitching, "keep", lambda df, label: seen.append(label) or kept(df, label))
    got = {r["rid"]: r for r in stitching._walk_on(unmet, adj, degree, 5, 9, "fix").collect()}
    assert not seen
    monkeypatch.setattr(walks, "LOCAL_EDGES", 1)
    want = {r["rid"]: r for r in stitching._walk_on(unmet, adj, degree, 5, 9, "fix").collect()}
    assert len(seen) == 5 and got == want and len(got) == 43
