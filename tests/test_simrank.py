"""Worked examples, closed forms, equivalences, expectations and controls."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from echowalk.functions import bounds
from echowalk.functions.rng import draw, draw_local
from echowalk.functions.sampling import SamplingPlan
from echowalk.operators import baselines, exact, meeting, metrics, pairs, primitives, walks
from echowalk.operators.stitching import Supply, stitched
from echowalk.plans import ledger, simrank, sql
from echowalk.sources import graphs, tables, workloads

C = 0.6


def rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


def scores(df):
    return {(r["a"], r["b"]): r["score"] for r in df.collect()}


@pytest.fixture(scope="module")
def knn(spark, sf):
    g = workloads.embedding_knn(spark, sf, 2)
    few = g.nodes.filter("id < 60")
    g = graphs.induced(g, few)
    return graphs.Graph(tables.keep(g.nodes), tables.keep(g.edges))


TUPLES = "pair int, step int, node long, walk_len int, start long"


def test_decompose_leaves_out_the_start(spark):
    w = spark.createDataFrame([(7, 1, 3, [10, 11, 12])], "start long, pair int, planned_len int, path array<long>")
    assert rows(walks.decompose(w), "pair", "step", "node", "walk_len", "start") == [(1, 1, 10, 3, 7), (1, 2, 11, 3, 7), (1, 3, 12, 3, 7)]


@pytest.mark.parametrize("method", list(meeting.METHODS))
def test_worked_meetings(spark, method):
    data = [
        (1, 1, 5, 3, 0), (1, 2, 6, 3, 0), (1, 3, 7, 3, 0),  # the source
        (1, 2, 6, 4, 1),  # meets at step 2
        (1, 2, 6, 2, 2), (1, 3, 7, 2, 2),  # twice, to be told once
        (2, 2, 6, 4, 3),  # another pair
        (1, 3, 6, 4, 4),  # another step
        (1, 1, 4, 4, 5),  # before any source tuple
    ]
    found = meeting.detect(spark.createDataFrame(data, TUPLES), 0, method)
    assert rows(found, *meeting.MEETS) == [(1, 0, 3, 1, 4), (1, 0, 3, 2, 2)]


def test_the_pair_has_to_agree(spark):
    data = [(1, 2, 6, 3, 0), (2, 2, 6, 4, 3)]
    df = spark.createDataFrame(data, TUPLES)
    assert meeting.by_global_predecessor(df, 0).count() == 0
    # a control without the check looks at step and node alone; the order by pair hides it here unless steps agree
    assert meeting.by_global_predecessor(df, 0, check_pair=False).count() == 1


def test_predecessor_across_partitions(spark):
    df = spark.createDataFrame([(i, 1 if i in (3, 50) else 0) for i in range(100)], "x long, lab int")
    out = {r["x"]: r["pred"] for r in primitives.predecessor(df, ["x"], F.col("lab") == 1, ["x"]).collect()}
    assert all((out[i]["x"] if out[i] else None) == (None if i < 3 else 3 if i < 50 else 50) for i in range(100))


def test_corners(spark):
    s = scores(exact.all_pairs(workloads.corner(spark, "siblings"), C, 5))
    assert s[2, 3] == pytest.approx(C) and (1, 2) not in s
    s = scores(exact.all_pairs(workloads.corner(spark, "star"), C, 5))
    assert all(s[a, b] == pytest.approx(C) for a in range(2, 6) for b in range(2, 6) if a != b)
    for name in ("cycle", "chain"):
        assert all(a == b for a, b in scores(exact.all_pairs(workloads.corner(spark, name), C, 5)))
    s = scores(exact.all_pairs(workloads.corner(spark, "two_levels"), C, 5))
    assert s[1, 2] == pytest.approx(C) and s[3, 4] == pytest.approx(C * C)
    s = scores(exact.all_pairs(workloads.corner(spark, "repeated"), C, 5))
    assert s[3, 4] == pytest.approx(C / 2)


def test_complete_bipartite_closed_form(spark):
    p, q = 2, 3
    m = np.linalg.solve([[1, -C * (q - 1) / q], [-C * (p - 1) / p, 1]], [C / q, C / p])
    s = scores(exact.all_pairs(workloads.corner(spark, "bipartite_2_3"), C, 40, tol=1e-9))
    assert s[1, 2] == pytest.approx(m[0], abs=1e-6) and s[3, 4] == pytest.approx(m[1], abs=1e-6) and (1, 3) not in s


def test_matrix_and_joins_agree(knn):
    edges, nodes = rows(knn.edges, "src", "dst"), [r[0] for r in rows(knn.nodes, "id")]
    m = exact.local_matrix(edges, nodes, C, 4)
    s = scores(exact.all_pairs(knn, C, 4))
    at = {v: k for k, v in enumerate(nodes)}
    assert max(abs(m[at[a], at[b]] - v) for (a, b), v in s.items()) < 1e-12 and (m > 0).sum() == len(s)


def test_strategies_walk_alike(knn):
    plan = SamplingPlan.create(60, C, 0.3)
    cols = walks.STEPS
    step = rows(walks.generate(knn, plan, 5, "stepwise"), *cols)
    assert step == rows(walks.generate(knn, plan, 5, "local"), *cols) == rows(walks.generate(knn, plan, 5, "local", "per_length"), *cols)
    edges = set(rows(knn.edges, "dst", "src"))
    by = {(s, w, k): n for s, w, _, k, n in step}
    assert all((by.get((s, w, k - 1), s), n) in edges for s, w, _, k, n in step)


def test_plan_numbers(spark, knn):
    plan = SamplingPlan.create(60, C, 0.3)
    got = {r["planned_len"]: r["n"] for r in walks.planned(knn, plan, 1).groupBy("planned_len").agg(F.count("*").alias("n")).collect()}
    assert got == {i: 60 * k for i, k in enumerate(plan.actual) if k}
    labels = walks.pre_permuted(knn, plan, 1)
    assert rows(labels, "start", "walk_no", "pair") == rows(walks.labels(walks.planned(knn, plan, 1), 1, "window"), "start", "walk_no", "pair")
    assert labels.groupBy("start").agg(F.count_distinct("pair").alias("n"), F.max("pair").alias("m"), F.min("pair").alias("l")).filter(f"n != {plan.total} or m != {plan.total} or l != 1").count() == 0
    with pytest.raises(ValueError):
        SamplingPlan.create(25, C, 0.12)
    assert SamplingPlan.create(25, C, 0.2).z == pytest.approx(305.6, abs=0.05)
    assert SamplingPlan.create(2100, C, 0.1).total == 444


def test_methods_give_the_same_scores(knn):
    best = exact.all_pairs(knn, C, 3).filter("a < b").orderBy(F.desc("score")).first()["a"]
    out = [rows(simrank.single_source(knn, best, C, 0.3, 3, strategy="local", method=m).withColumn("score", F.round("score", 9)), "node", "score") for m in ("fused", "broadcast_join", "predecessor")]
    assert out[0] == out[1] == out[2] and len(out[0]) > 1


def test_error_bound_and_zero_vector(knn):
    truth = exact.all_pairs(knn, C, 12).cache()
    best = truth.filter("a < b").orderBy(F.desc("score")).first()
    t = truth.filter(F.col("a") == best["a"]).select(F.col("a").alias("source"), F.col("b").alias("node"), "score")
    est = simrank.single_source(knn, best["a"], C, 0.15, 11, scope="all_nodes", strategy="local", method="broadcast_join")
    assert metrics.max_abs_error(est, t).first()[1] <= 0.15
    assert metrics.max_abs_error(t.filter("false"), t).first()[1] > 0.15


def test_mean_meets_the_expectation(knn):
    truth = exact.all_pairs(knn, C, 3)
    best = truth.filter("a < b").orderBy(F.desc("score")).first()
    s, u = best["a"], best["b"]
    plan = SamplingPlan.create(60, C, 0.3)
    only = knn.nodes.filter(F.col("id").isin(s, u)).select("id")
    for how in ("ideal", "unbiased"):
        want = exact.expected_estimate(knn, s, plan, how).filter(F.col("node") == u).first()["score"]
        got = []
        for seed in range(4):
            t = simrank.labelled_tuples(knn, plan, seed, "local", starts=only)
            r = meeting.aggregate(meeting.by_join(t, s), plan, how).filter(F.col("node") == u).first()
            got.append(r["score"] if r else 0.0)
        assert np.mean(got) == pytest.approx(want, abs=4 * math.sqrt(0.25 / plan.total / len(got)))


def test_stitched_walks(spark, knn):
    plan = SamplingPlan.create(60, C, 0.4)
    walkers = walks.planned(knn, plan, 2)
    adj = walks.prepared(knn)
    steps, short = stitched(knn, plan, walkers, adj, 2, Supply(pilot=4))
    data = rows(steps, *walks.STEPS)
    edges = set(rows(knn.edges, "dst", "src"))
    by = {(s, w, k): n for s, w, _, k, n in data}
    assert all((by.get((s, w, k - 1), s), n) in edges and k <= p for s, w, p, k, n in data)
    dead = {r[0] for r in rows(graphs.dead_ends(knn), "node")}
    made: dict = {}
    for s, w, p, k, n in data:
        made[s, w] = max(made.get((s, w), (0, 0)), (k, n))
    lens = {(s, w): p for s, w, p in rows(walkers, "start", "walk_no", "planned_len")}
    for key, p in lens.items():
        k, end = made.get(key, (0, key[0]))
        assert k == p or end in dead
    assert short.agg(F.sum("missing")).first()[0] >= 0


def test_warm_up_and_pairs(spark, knn):
    g = workloads.corner(spark, "siblings")
    r = pairs.monte_carlo(g, 2, 3, 2000, C, 1).first()
    assert abs(r["score"] - C) < 3 * r["half_width"] and r["half_width"] == pytest.approx(bounds.half_width(2000, 0.05))
    est = {x["node"]: x["score"] for x in simrank.warm_up(g, 2, C, 0.2, 1, n=20).collect()}
    assert abs(est[3] - C) < 0.2 and est[2] == 1.0 and 1 not in est
    coin = {x["node"]: x["score"] for x in simrank.warm_up(g, 2, C, 0.2, 1, n=20, coin="per_step").collect()}
    assert abs(coin[3] - C) < 0.2


def test_baselines(spark):
    g = workloads.corner(spark, "bipartite_2_3")
    truth = scores(exact.all_pairs(g, C, 30))
    got = {r["node"]: r["score"] for r in baselines.linear_forest(g, 3, C, 12, diagonal="exact").collect()}
    assert got[4] == pytest.approx(truth[3, 4], abs=0.02)
    jac = {r["node"]: r["score"] for r in baselines.linear_jacobi(g, 3, C, 10, jacobi_iters=20, rows="exact").collect()}
    assert jac[4] == pytest.approx(truth[3, 4], abs=0.02)
    und = graphs.from_edges(g.edges, directed=False)
    uni = {r["node"]: r["score"] for r in baselines.unidirectional(und, 3, C, 6, 3000, 1).collect()}
    assert uni[4] == pytest.approx(truth[3, 4], abs=0.06)
    with pytest.raises(ValueError):
        baselines.unidirectional(g, 3)
    mc = {r["node"]: r["score"] for r in baselines.linear_forest(g, 3, C, 8, seed=3, pairs=400, diagonal="forest").collect()}
    assert mc[4] == pytest.approx(truth[3, 4], abs=0.1)


def test_graph_tables(spark):
    e = spark.createDataFrame([(1, 2), (1, 2), (None, 3), (3, 3), (4, 2)], "src long, dst long")
    g = graphs.from_edges(e)
    assert rows(g.edges, "src", "dst") == [(1, 2), (3, 3), (4, 2)]
    assert rows(graphs.from_edges(e, drop_self_loops=True).edges, "src", "dst") == [(1, 2), (4, 2)]
    assert rows(graphs.ranked_adjacency(g), "node", "rk", "nbr", "nbr_deg") == [(2, 0, 1, 0), (2, 1, 4, 0), (3, 0, 3, 1)]
    assert rows(graphs.degrees(g), "node", "degree") == sorted(rows(primitives.degrees_by_placeholder(g.edges, g.nodes), "node", "degree"))
    d, to = graphs.dense_ids(g)
    assert rows(d.nodes, "id") == [(1,), (2,), (3,), (4,)]
    empty = graphs.from_edges(e.filter("false"))
    assert graphs.ranked_adjacency(empty).count() == 0


def test_draws_agree(spark):
    r = spark.range(3).select(draw(9, "x", F.col("id"), F.lit(4)).alias("h")).collect()
    assert [x["h"] for x in r] == [draw_local(9, "x", i, 4) for i in range(3)]


def test_bounds_and_ledger(spark, knn):
    assert bounds.min_alpha(22_000, C) is None and bounds.min_alpha(10**9, C) == pytest.approx(0.797, abs=0.01)
    assert bounds.owner(5, 10, 2) == 1 and bounds.owner(6, 10, 2) == 2
    assert bounds.warm_up_length(2200, 0.1, C) == pytest.approx(118, abs=1)
    assert ledger.rounds_of("stepwise", 24) == 24 and ledger.rounds_of("local", 24) == 0 and ledger.rounds_of("stitched", 24) < 24
    book = ledger.Ledger(spark, 60).add("edges", "distinct", knn.edges.distinct())
    assert book.frame().first()["total_rows"] == knn.edges.count()


def test_sql_surface(spark, sf):
    sql.register_views(spark, sf, ["nation"])
    assert spark.sql("SELECT count(*) FROM nation").first()[0] == 25
    sql.register_functions(spark)
    assert [tuple(r) for r in spark.sql("SELECT * FROM decompose_walk(array(5L, 6L))").collect()] == [(1, 5), (2, 6)]


def test_streams(spark, sf, tmp_path):
    from echowalk.streaming import edges as streaming

    src = tmp_path / "events"
    tables.read(spark, sf, "events").coalesce(1).write.parquet(str(src))
    q = streaming.windowed_counts(streaming.fresh(streaming.events(spark, str(src))), "tumbling", "1 day").writeStream.outputMode("append").format("memory").queryName("counted").start()
    q.processAllAvailable()
    q.stop()
    assert spark.sql("SELECT count(*) FROM counted").first()[0] > 0
    got = []
    flow = streaming.transitions(streaming.events(spark, str(src)))
    q = streaming.rolling_scores(flow, lambda g: exact.all_pairs(g, C, 1), lambda df, n: got.append(df.count()), str(tmp_path / "edges")).option("checkpointLocation", str(tmp_path / "cp")).start()
    q.processAllAvailable()
    q.stop()
    assert got and got[-1] > 0
