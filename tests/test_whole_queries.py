"""Registered queries over whole tables, against brute force."""

from collections import defaultdict

import pytest

from echowalk.operators import exact
from echowalk.plans import catalogue
from echowalk.sources import workloads


def test_user_scores_take_all_events(spark, sf):
    e = [r["user_id"] for r in spark.read.parquet(f"{sf}/events.parquet").orderBy("ts", "event_id").collect()]
    edges = sorted({(a, b) for a, b in zip(e, e[1:]) if a != b})
    nodes = sorted({x for p in edges for x in p})
    want = exact.local_matrix(edges, nodes, catalogue.C, 5)[0]
    got = {r["node"]: r["score"] for r in catalogue.QUERIES["exact_single_source_users_all_events"](spark, sf).collect()}
    assert [got.get(n, 0.0) for n in nodes] == pytest.approx(list(want), abs=1e-8)


def test_conversation_graph_has_frequent_words(spark, sf, tmp_path):
    rows = [(i, 0, "user", f"the w{'ab'[i % 2]} once{'abcdefghijklmnopqrstuvwxyz'[i % 26] * (1 + i // 26)}") for i in range(120)]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    got = catalogue.QUERIES["graph_conversation_all_tokens"](spark, str(tmp_path)).collect()
    degree = defaultdict(set)
    for r in got:
        if r["dst"] % 2:
            degree[r["dst"]].add(r["src"])
    assert sorted(len(x) for x in degree.values()) == [60, 60, 120]


def test_conversation_graph_equals_its_sql(spark, sf):
    import duckdb

    db = duckdb.connect()
    db.execute(f"CREATE VIEW conversations AS SELECT * FROM '{sf}/conversations.parquet'")
    want = db.execute(catalogue.ORACLE_SQL["graph_conversation_all_tokens"]).fetchall()
    assert sorted(tuple(r) for r in catalogue.QUERIES["graph_conversation_all_tokens"](spark, sf).collect()) == sorted(want)


def test_shortfall_of_the_page_graph(spark, sf, monkeypatch):
    seen = []

    def spy(g, plan, planned, adj, seed, supply):
        seen.append((g.size(), supply.pilot, supply.slack, planned.count() // g.size()))
        return None, spark.createDataFrame([(0, 0)], "level int, missing long")

    monkeypatch.setattr(catalogue, "stitched", spy)
    catalogue.QUERIES["stitched_shortfall_by_slack"](spark, sf)
    pages = workloads.page_links(spark, sf, directed=False)
    assert [x[:3] for x in seen] == [(pages.size(), 4, s) for s in (1.0, 1.5, 1.0)] and seen[0][3] > 50


def test_linear_baselines_run_on_the_page_graph(spark, sf):
    got = {r["method"]: r for r in catalogue.QUERIES["error_summary_by_method"](spark, sf).collect()}
    for name in ("linear_jacobi", "linear_pair_diagonal", "linear_exact_diagonal"):
        assert 0 <= got[name]["max_abs_error"] < 0.15
    assert got["linear_exact_diagonal"]["max_abs_error"] < 0.02
