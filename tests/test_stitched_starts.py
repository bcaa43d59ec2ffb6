"""Segments are made for the walks that are asked for, not for walks of every node."""

from pyspark.sql import functions as F

from echowalk.functions.sampling import SamplingPlan
from echowalk.operators import stitching, walks
from echowalk.sources import graphs


def test_no_segments_where_no_walk_leads(spark, monkeypatch):
    ring = lambda a, n: [(a + k, a + (k + 1) % n) for k in range(n)] + [(a + k, a + (k + 2) % n) for k in range(n)]
    g = graphs.from_edges(spark.createDataFrame(ring(0, 5) + ring(100, 7), "src long, dst long"))
    plan, adj, seen = SamplingPlan.create(12, 0.6, 0.4), walks.prepared(g), []
    make = stitching.supplies
    monkeypatch.setattr(stitching, "supplies", lambda *a: seen.append(make(*a)) or seen[-1])
    walkers = walks.planned(g, plan, 3, spark.createDataFrame([(1,), (2,)], "id long"))
    steps, _ = stitching.stitched(g, plan, walkers, adj, 3)
    for supply in seen[0].values():
        total = supply.groupBy((F.col("node") >= 100).alias("other")).agg(F.sum(F.col("use") + F.col("heads") + F.col("tails")).alias("n"))
        assert {r["other"]: r["n"] > 0 for r in total.collect()} == {False: True, True: False}
    got = {(r["start"], r["walk_no"]): r["n"] for r in steps.groupBy("start", "walk_no").agg(F.count("step").alias("n")).collect()}
    want = {(r["start"], r["walk_no"]): r["planned_len"] for r in walkers.collect() if r["planned_len"]}
    assert got == want
