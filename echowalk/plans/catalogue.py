"""Queries for the driver, one or more for each method, operator, measure and workload, and DuckDB
SQL that replays those it can express."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import bounds
from ..functions.rng import SPAN, draw_sql
from ..functions.sampling import SamplingPlan
from ..operators import baselines, exact, index, meeting, metrics, pairs, primitives, walks
from ..operators.stitching import Supply, stitched
from ..sources import graphs, tables, workloads
from . import ledger, simrank, sql

C, SEED, EPS = 0.6, 42, 0.2
SOURCE = 1  # the first target of page links
QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def nearest(df: DataFrame, col: str) -> DataFrame:
    """To 9 digits, in doubles alone: closed forms are often halves of the last digit."""
    return df.withColumn(col, F.floor(F.col(col) * 1e9 + 0.5).cast("double") / F.lit(1e9))


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle is not None:
            ORACLE_SQL[f.__name__] = oracle
        return f

    return add


def rounded(df: DataFrame, *cols: str, digits: int = 9) -> DataFrame:
    return df.withColumns({c: F.round(c, digits) + F.lit(0.0) for c in cols})


# --- graphs -----------------------------------------------------------------------------------

_BOTH = "SELECT src, dst FROM {0} UNION SELECT dst AS src, src AS dst FROM {0}"
_LINKS = """links AS (SELECT DISTINCT page_id * 2 AS src, target FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS target FROM pages)),
    targets AS (SELECT target, (row_number() OVER (ORDER BY target) - 1) * 2 + 1 AS id FROM (SELECT DISTINCT target FROM links)),
    directed AS (SELECT DISTINCT src, id AS dst FROM links JOIN targets USING (target))"""
_PAGES = f"{_LINKS}, edges AS ({_BOTH.format('directed')})"
_ADJ = """degree AS (SELECT dst AS node, count(*) AS deg FROM edges GROUP BY dst),
    adj AS (SELECT e.dst AS node, row_number() OVER (PARTITION BY e.dst ORDER BY e.src) - 1 AS rk, e.src AS nbr, coalesce(d.deg, 0) AS nbr_deg, own.deg AS node_deg
        FROM edges e LEFT JOIN degree d ON d.node = e.src JOIN degree own ON own.node = e.dst),
    nodes AS (SELECT DISTINCT src AS id FROM edges UNION SELECT dst FROM edges)"""


def _edges(g: graphs.Graph) -> DataFrame:
    return g.edges.select("src", "dst")


@query(f"WITH p AS (SELECT DISTINCT l_partkey * 2 AS src, l_suppkey * 2 + 1 AS dst FROM lineitem) {_BOTH.format('p')}")
def graph_part_supplier_edges(spark, d):
    return _edges(workloads.part_supplier(spark, d))


_CP = "p AS (SELECT DISTINCT o_custkey * 2 AS src, l_partkey * 2 + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey)"


@query(f"WITH {_CP} {_BOTH.format('p')}")
def graph_customer_part_edges(spark, d):
    return _edges(workloads.customer_part(spark, d))


@query(f"WITH {_CP} SELECT src, dst FROM p")
def graph_customer_part_directed_edges(spark, d):
    return _edges(workloads.customer_part(spark, d, directed=True))


@query(f"WITH {_LINKS} SELECT src, dst FROM directed")
def graph_page_links(spark, d):
    return _edges(workloads.page_links(spark, d))


@query(f"WITH {_PAGES} SELECT src, dst FROM edges")
def graph_page_links_undirected(spark, d):
    return _edges(workloads.page_links(spark, d, directed=False))


@query("""WITH l AS (SELECT DISTINCT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS target FROM pages),
    h AS (SELECT host, (row_number() OVER (ORDER BY host) - 1) * 2 AS id FROM (SELECT DISTINCT host FROM l)),
    t AS (SELECT target, (row_number() OVER (ORDER BY target) - 1) * 2 + 1 AS id FROM (SELECT DISTINCT target FROM l))
    SELECT DISTINCT h.id AS src, t.id AS dst FROM l JOIN h USING (host) JOIN t USING (target)""")
def graph_host_links(spark, d):
    return _edges(workloads.page_links(spark, d, level="host"))


_USERS = """e AS (SELECT user_id, lead(user_id) OVER (ORDER BY ts, event_id) AS nxt FROM events {0}),
    edges AS (SELECT DISTINCT user_id AS src, nxt AS dst FROM e WHERE nxt IS NOT NULL AND nxt <> user_id)"""


@query(f"WITH {_USERS.format('')} SELECT src, dst FROM edges")
def graph_user_transition(spark, d):
    return _edges(workloads.user_transition(spark, d))


_TRADE = """edges AS (SELECT DISTINCT CAST(c_nationkey AS BIGINT) AS src, CAST(s_nationkey AS BIGINT) AS dst
    FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey
    WHERE o_totalprice > {0} AND o_orderpriority = '1-URGENT' AND l_quantity >= 45)"""


@query(f"WITH {_TRADE.format(300000)} SELECT src, dst FROM edges")
def graph_nation_trade(spark, d):
    return _edges(workloads.nation_trade(spark, d))


@query("""WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings),
    s AS (SELECT vec_id, v, sqrt(list_inner_product(v, v)) AS size FROM v),
    p AS (SELECT a.vec_id AS src, b.vec_id AS dst, round(list_inner_product(a.v, b.v) / (a.size * b.size), 9) AS cosine FROM s a JOIN s b ON a.vec_id <> b.vec_id)
    SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY cosine DESC, dst) AS rn FROM p) WHERE rn <= 2""")
def graph_embedding_knn(spark, d):
    return _edges(workloads.embedding_knn(spark, d, 2))


@query("""WITH l AS (SELECT DISTINCT doc_id, trim(line, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE trim(line, ' ') <> ''),
    k AS (SELECT line, row_number() OVER (ORDER BY line) - 1 AS rank FROM (SELECT line FROM l GROUP BY line HAVING count(DISTINCT doc_id) >= 2)),
    p AS (SELECT DISTINCT doc_id * 2 AS src, rank * 2 + 1 AS dst FROM l JOIN k USING (line)) SELECT src, dst FROM p UNION SELECT dst, src FROM p""")
def graph_doc_lines(spark, d):
    return _edges(workloads.doc_lines(spark, d))


@query("""WITH w AS (SELECT DISTINCT conv_id, word FROM (SELECT conv_id, unnest(string_split_regex(lower(text), '[^a-z]+')) AS word FROM conversations WHERE role = 'user') WHERE word <> ''),
    k AS (SELECT word, row_number() OVER (ORDER BY word) - 1 AS rank FROM (SELECT word FROM w GROUP BY word HAVING count(DISTINCT conv_id) BETWEEN 2 AND 50)),
    p AS (SELECT DISTINCT conv_id * 2 AS src, rank * 2 + 1 AS dst FROM w JOIN k USING (word)) SELECT src, dst FROM p UNION SELECT dst, src FROM p""")
def graph_conversation_tokens(spark, d):
    return _edges(workloads.conversation_tokens(spark, d, max_df=50))


@query("""WITH w AS (SELECT DISTINCT conv_id, word FROM (SELECT conv_id, unnest(string_split_regex(lower(text), '[^a-z]+')) AS word FROM conversations WHERE role = 'user') WHERE word <> ''),
    k AS (SELECT word, row_number() OVER (ORDER BY word) - 1 AS rank FROM (SELECT word FROM w GROUP BY word HAVING count(DISTINCT conv_id) >= 2)),
    p AS (SELECT DISTINCT conv_id * 2 AS src, rank * 2 + 1 AS dst FROM w JOIN k USING (word)) SELECT src, dst FROM p UNION SELECT dst, src FROM p""")
def graph_conversation_all_tokens(spark, d):
    """The graph above without its upper bound, which drops more words the more conversations there are."""
    return _edges(workloads.conversation_tokens(spark, d))


@query(f"WITH {_PAGES}, {_ADJ} SELECT node, CAST(rk AS INTEGER) AS rk, nbr, CAST(nbr_deg AS INTEGER) AS nbr_deg, CAST(node_deg AS INTEGER) AS node_deg FROM adj")
def ranked_adjacency(spark, d):
    return graphs.ranked_adjacency(workloads.page_links(spark, d, directed=False))


@query(f"WITH {_LINKS} SELECT DISTINCT src AS node FROM directed WHERE src NOT IN (SELECT dst FROM directed)")
def dead_end_nodes(spark, d):
    return graphs.dead_ends(workloads.page_links(spark, d)).select("node")


@query(f"WITH {_PAGES} SELECT dst AS node, count(*) AS degree FROM edges GROUP BY dst")
def degrees_by_placeholder(spark, d):
    g = workloads.page_links(spark, d, directed=False)
    return primitives.degrees_by_placeholder(g.edges, g.nodes)


@query(f"WITH {_PAGES}, n AS (SELECT DISTINCT src AS old FROM edges), m AS (SELECT old, row_number() OVER (ORDER BY old) AS id FROM n) SELECT a.id AS src, b.id AS dst FROM edges JOIN m a ON edges.src = a.old JOIN m b ON edges.dst = b.old")
def dense_ids_edges(spark, d):
    return _edges(graphs.dense_ids(workloads.page_links(spark, d, directed=False))[0])


@query("SELECT o_orderkey, o_totalprice, row_number() OVER (ORDER BY o_totalprice, o_orderkey) - 1 AS rank FROM orders")
def global_rank_orders(spark, d):
    return primitives.global_rank(tables.read(spark, d, "orders").select("o_orderkey", "o_totalprice"), ["o_totalprice", "o_orderkey"]).select("o_orderkey", "o_totalprice", "rank")


@query("""SELECT event_id, last_value(CASE WHEN event_type = 'error' THEN event_id END IGNORE NULLS) OVER (ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS last_error FROM events""")
def global_predecessor_events(spark, d):
    e = tables.read(spark, d, "events").select("event_id", "ts", "event_type")
    return primitives.predecessor(e, ["ts", "event_id"], F.col("event_type") == "error", ["event_id"]).select("event_id", F.col("pred.event_id").alias("last_error"))


@query(f"WITH {_PAGES} SELECT dst AS node, CAST(ceil(dst * 4 / (SELECT max(dst) FROM edges)) AS INTEGER) AS owner, count(*) AS degree FROM edges GROUP BY dst")
def owner_ranges(spark, d):
    g = workloads.page_links(spark, d, directed=False)
    top = g.edges.agg(F.max("dst")).first()[0]
    return graphs.degrees(g).select("node", primitives.owner(F.col("node"), top, 4).alias("owner"), "degree")


@query("""SELECT time_bucket(INTERVAL 1 DAY, ts) AS window_start, user_id AS src, event_type AS dst, count(*) AS n FROM events GROUP BY 1, 2, 3""")
def windowed_event_edges(spark, d):
    return graphs.windowed_edges(tables.read(spark, d, "events"), "user_id", "event_type", "ts", "1 day")


# --- plans --------------------------------------------------------------------------------------

_N = "n AS (SELECT count(*) AS n FROM nodes)"


def _plan(eps: float = EPS, scope: str = "n", whole: str = "ceil", clip: bool = False) -> str:
    """plan(len, ideal, actual), const(n, z, r, last), over nodes."""
    tail = "CASE WHEN i = last THEN z * pow(r, i) ELSE z * pow(r, i) * (1 - r) END" if clip else "z * pow(r, i) * (1 - r)"
    return f"""{_N}, const AS (SELECT n, ln(2.0 * {scope}) / (2 * pow({eps} - 3.0 / n, 2)) AS z, sqrt(CAST({C} AS DOUBLE)) AS r, CAST(floor(ln(n) / ln(1 / sqrt(CAST({C} AS DOUBLE))) + 1e-9) AS BIGINT) AS last FROM n),
    plan AS (SELECT i AS len, {tail} AS ideal, CAST({whole}({tail}) AS BIGINT) AS actual FROM const, range(0, 200) t(i) WHERE i <= last)"""


def _plan_query(name: str, **how):
    sql_how = {"scope": "n * n" if how.get("scope") == "all_nodes" else "n", "whole": how.get("rounding", "ceil"), "clip": how.get("truncation") == "clip"}

    def run(spark, d):
        g = workloads.page_links(spark, d, directed=False)
        plan = SamplingPlan.create(g.size(), C, EPS, **how)
        return rounded(plan.frame(spark).select("len", "ideal", "actual", "lo", "hi"), "ideal", digits=6)

    run.__name__ = name
    query(f"""WITH {_PAGES}, {_ADJ}, {_plan(**sql_how)} SELECT CAST(len AS INTEGER) AS len, round(ideal, 6) AS ideal, CAST(actual AS INTEGER) AS actual,
        CAST(sum(actual) OVER (ORDER BY len) - actual AS INTEGER) AS lo, CAST(sum(actual) OVER (ORDER BY len) AS INTEGER) AS hi FROM plan""")(run)


_plan_query("length_plan_ceil")
_plan_query("length_plan_floor", rounding="floor")
_plan_query("length_plan_clip", truncation="clip")
_plan_query("length_plan_all_nodes", scope="all_nodes")


#: Sizes of the graphs of the given tables: the nodes that edges have, and distinct edges.
_SIZES = {
    "customer_part": "SELECT o_custkey * 2 AS src, l_partkey * 2 + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_custkey IS NOT NULL AND l_partkey IS NOT NULL",
    "part_supplier": "SELECT l_partkey * 2 AS src, l_suppkey * 2 + 1 AS dst FROM lineitem WHERE l_partkey IS NOT NULL AND l_suppkey IS NOT NULL",
    "user_transition": "SELECT src, dst FROM (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL AND src <> dst",
}
_SIZES_SQL = ", ".join([f"e_{k} AS (SELECT DISTINCT src, dst FROM ({x}))" for k, x in _SIZES.items()]) + ", sizes AS (" + " UNION ALL ".join(f"SELECT '{k}' AS graph, (SELECT count(*) FROM (SELECT src FROM e_{k} UNION SELECT dst FROM e_{k})) AS n, (SELECT count(*) FROM e_{k}) AS m" for k in _SIZES) + ")"


def _graph_sizes(spark, d) -> list[tuple[str, int, int]]:
    graphs_of = {"customer_part": lambda: workloads.customer_part(spark, d, directed=True), "user_transition": lambda: workloads.user_transition(spark, d)}
    out = []
    for name in _SIZES:
        edges = graphs_of[name]().edges if name in graphs_of else workloads.part_supplier(spark, d).edges.filter("src % 2 = 0")
        edges = tables.keep(edges.select("src", "dst"), "sized")
        out.append((name, edges.select("src").union(edges.select("dst")).distinct().count(), edges.count()))
    return out


@query(f"WITH {_SIZES_SQL} SELECT graph, n, CAST(ceil(ln(2.0 * n * n) / (2 * 0.1 * 0.1)) AS INTEGER) AS walks, CAST(ceil(3 * ln(n / CAST(0.1 AS DOUBLE)) / ln(1 / sqrt(CAST(0.6 AS DOUBLE)))) AS INTEGER) AS most FROM sizes")
def warmup_size(spark, d):
    """Walks of a node and their longest length on the graphs of the given tables."""
    return spark.createDataFrame([(g, n, math.ceil(bounds.warm_up_walks(n, 0.1)), math.ceil(bounds.warm_up_length(n, 0.1, C))) for g, n, _ in _graph_sizes(spark, d)], "graph string, n long, walks int, most int")


@query(f"""WITH {_SIZES_SQL}, g AS (SELECT graph, CAST(n AS DOUBLE) AS n, CAST(m AS DOUBLE) AS m, CAST(0.1 AS DOUBLE) AS eps FROM sizes)
    SELECT graph, 'fixed_length' AS method, CAST(n AS BIGINT) AS n, eps, round(pow(ln(greatest(ln(n), exp(1.0))), 2), 6) AS rounds, round(m * ln(n) + n * pow(ln(n), 4.5) + n * pow(ln(n), 3) / (2 * pow(eps - 3 / n, 2)), -3) AS space, eps AS error FROM g
    UNION ALL SELECT graph, 'warm_up', CAST(n AS BIGINT), eps, round(ln(n / eps), 6), round(n * ln(n) * ln(n / eps) / (eps * eps), -3), eps FROM g
    UNION ALL SELECT graph, 'linear_jacobi', CAST(n AS BIGINT), eps, round(n * 10 * 15 / 100, 6), round(100 * 100 * ln(n) / (eps * eps) + n + m, -3), NULL FROM g
    UNION ALL SELECT graph, 'unidirectional', CAST(n AS BIGINT), eps, 10.0, round(n * n * 10 * ln(n) / (eps * eps), -3), eps FROM g
    UNION ALL SELECT graph, 'linear_forest', CAST(n AS BIGINT), eps, round(pow(ln(n), 2) / (eps * eps) + 10, 6), round(m * ln(n) + 10 * n, -3), round(0.6 * (1 - pow(0.6, 10)) * eps / 0.4 + pow(0.6, 11), 9) FROM g""")
def bounds_table(spark, d):
    """Rounds, space and error of each method on the graphs of the given tables."""
    rows, eps = [], 0.1
    for graph, n, m in _graph_sizes(spark, d):
        for name, f in bounds.METHODS.items():
            rounds, space, error = f(n, m, eps, C)
            rows.append((graph, name, n, eps, float(round(rounds, 6)), float(round(space, -3)), None if error is None else round(error, 9)))
    return spark.createDataFrame(rows, "graph string, method string, n long, eps double, rounds double, space double, error double")


# --- exact --------------------------------------------------------------------------------------


def _exact(iterations: int) -> str:
    """s<k>(a, b, score) over adj, diagonal included."""
    parts = ["p AS (SELECT node, nbr, 1.0 / node_deg AS p FROM (SELECT dst AS node, src AS nbr, count(*) OVER (PARTITION BY dst) AS node_deg FROM edges))", "s0 AS (SELECT id AS a, id AS b, CAST(1 AS DOUBLE) AS score FROM nodes)"]
    for k in range(1, iterations + 1):
        parts.append(f"""s{k} AS (SELECT x.node AS a, y.node AS b, CAST({C} AS DOUBLE) * sum(s.score * x.p * y.p) AS score FROM s{k - 1} s JOIN p x ON x.nbr = s.a JOIN p y ON y.nbr = s.b WHERE x.node <> y.node GROUP BY 1, 2
            UNION ALL SELECT id, id, 1 FROM nodes)""")
    return ", ".join(parts)


_TRADE_NODES = "nodes AS (SELECT CAST(n_nationkey AS BIGINT) AS id FROM nation)"


@query(f"WITH {_TRADE.format(300000)}, {_TRADE_NODES}, {_exact(6)} SELECT a, b, round(score, 9) AS score FROM s6")
def exact_all_pairs_nation(spark, d):
    return rounded(exact.all_pairs(workloads.nation_trade(spark, d), C, 6), "score")


_DAY = _USERS.format("WHERE ts < TIMESTAMP '2024-01-02'")
_EDGE_NODES = "nodes AS (SELECT DISTINCT src AS id FROM edges UNION SELECT dst FROM edges)"


@query(f"WITH {_DAY}, {_EDGE_NODES}, {_exact(5)}, f AS (SELECT min(id) AS id FROM nodes) SELECT a AS source, b AS node, round(score, 9) AS score FROM s5, f WHERE a = f.id")
def exact_single_source_users(spark, d):
    g = workloads.user_transition(spark, d, end="2024-01-02")
    first = g.nodes.agg(F.min("id")).first()[0]
    return rounded(exact.single_source(g, first, C, 5), "score")


@query()
def exact_single_source_users_all_events(spark, d):
    """The query above over the whole table; its SQL covers one day only."""
    g = workloads.user_transition(spark, d)
    return rounded(exact.single_source(g, g.nodes.agg(F.min("id")).first()[0], C, 5), "score")


@query(f"""WITH {_CP}, k AS (SELECT dst, count(*) AS deg FROM p GROUP BY dst)
    SELECT x.dst AS a, y.dst AS b, CAST(floor(CAST({C} AS DOUBLE) * count(*) / (kx.deg * ky.deg) * 1e9 + 0.5) AS DOUBLE) / 1e9 AS score FROM p x JOIN p y ON x.src = y.src AND x.dst < y.dst JOIN k kx ON kx.dst = x.dst JOIN k ky ON ky.dst = y.dst GROUP BY 1, 2, kx.deg, ky.deg""")
def closed_form_customer_part(spark, d):
    return nearest(exact.closed_form_two_sided(workloads.customer_part(spark, d, directed=True), C), "score")


_TARGET_PAIRS = f"""SELECT x.dst AS a, y.dst AS b, CAST(floor(CAST({C} AS DOUBLE) * count(*) / (kx.deg * ky.deg) * 1e9 + 0.5) AS DOUBLE) / 1e9 AS score FROM directed x JOIN directed y ON x.src = y.src AND x.dst < y.dst
    JOIN k kx ON kx.dst = x.dst JOIN k ky ON ky.dst = y.dst GROUP BY 1, 2, kx.deg, ky.deg"""


@query(f"WITH {_LINKS}, k AS (SELECT dst, count(*) AS deg FROM directed GROUP BY dst) {_TARGET_PAIRS}")
def closed_form_page_targets(spark, d):
    """The recursion itself, which on this graph must give the closed form that the SQL has."""
    return nearest(exact.all_pairs(workloads.page_links(spark, d), C, 3).filter("a < b").withColumn("score", F.round("score", 14)), "score")


# --- walks --------------------------------------------------------------------------------------


def _walks(seed: int = SEED) -> str:
    """planned(start, walk_no, planned_len) is to be there; gives steps and tuples."""
    step = draw_sql(seed, "step", "w.start", "w.walk_no", "w.step + 1")
    perm = draw_sql(seed, "perm", "start", "walk_no")
    return f"""w AS (
        SELECT start, walk_no, planned_len, CAST(0 AS BIGINT) AS step, start AS node, coalesce(deg, 0) AS deg FROM planned LEFT JOIN degree ON degree.node = planned.start
        UNION ALL
        SELECT w.start, w.walk_no, w.planned_len, w.step + 1, a.nbr, a.nbr_deg FROM w JOIN adj a ON a.node = w.node AND a.rk = {step} % w.deg WHERE w.step < w.planned_len AND w.deg > 0),
    steps AS (SELECT start, walk_no, planned_len, step, node FROM w WHERE step > 0),
    labels AS (SELECT start, walk_no, planned_len, row_number() OVER (PARTITION BY start ORDER BY {perm}, walk_no) AS pair FROM planned),
    tuples AS (SELECT l.pair, s.step, s.node, s.planned_len AS walk_len, s.start FROM steps s JOIN labels l ON l.start = s.start AND l.walk_no = s.walk_no)"""


_PLANNED = """lens AS (SELECT len, row_number() OVER (ORDER BY len) AS walk_no FROM (SELECT len, unnest(range(actual)) AS k FROM plan)),
    planned AS (SELECT id AS start, walk_no, len AS planned_len FROM nodes, lens)"""


def _sampled(graph: str = _PAGES, eps: float = EPS, source: str = str(SOURCE), **how) -> str:
    return f"WITH RECURSIVE {graph}, {_ADJ}, {_plan(eps, **how)}, {_PLANNED}, {_walks()}, src AS (SELECT CAST({source} AS BIGINT) AS id)"


_MEETS = "meets AS (SELECT DISTINCT t.pair, s.start AS source, s.walk_len AS source_len, t.start AS target, t.walk_len AS target_len FROM tuples t JOIN tuples s USING (pair, step, node) JOIN src ON s.start = src.id WHERE t.start <> s.start)"


def _scores(normalization: str) -> str:
    weight = {"ideal": "ps.ideal / ps.actual * pt.ideal / pt.actual / z", "unbiased": "ps.ideal / ps.actual * pt.ideal / pt.actual * total / (z * z)", "plain": "1.0 / total"}[normalization]
    return f"""{_MEETS}, total AS (SELECT sum(actual) AS total FROM plan),
    scores AS (SELECT source, target AS node, sum({weight}) AS score FROM meets JOIN plan ps ON ps.len = source_len JOIN plan pt ON pt.len = target_len, const, total GROUP BY source, target
        UNION ALL SELECT id, id, 1 FROM src)"""


def _pages(spark, d):
    return workloads.page_links(spark, d, directed=False)


def _planned_of(g, **how):
    return SamplingPlan.create(g.size(), C, how.pop("eps", EPS), **how)


_STEPS_OUT = "SELECT start, CAST(walk_no AS INTEGER) AS walk_no, CAST(planned_len AS INTEGER) AS planned_len, CAST(step AS INTEGER) AS step, node FROM steps"


@query(f"{_sampled()} {_STEPS_OUT}")
def walks_stepwise(spark, d):
    g = _pages(spark, d)
    return walks.generate(g, _planned_of(g), SEED, "stepwise")


@query(f"{_sampled()} {_STEPS_OUT}")
def walks_local(spark, d):
    g = _pages(spark, d)
    return walks.generate(g, _planned_of(g), SEED, "local")


@query(f"{_sampled(_TRADE.format(300000))} {_STEPS_OUT}")
def walks_per_length(spark, d):
    g = workloads.nation_trade(spark, d)
    g = graphs.from_edges(g.edges)
    return walks.generate(g, _planned_of(g), SEED, "local", "per_length")


@query(f"{_sampled(_TRADE.format(300000))} {_STEPS_OUT}")
def walks_recursive_sql(spark, d):
    g = graphs.from_edges(workloads.nation_trade(spark, d).edges)
    plan = _planned_of(g)
    sql.register_graph(g, "trade")
    walks.planned(g, plan, SEED).createOrReplaceTempView("trade_walkers")
    return sql.recursive_walks(spark, "trade_adj", "trade_walkers", SEED, plan.longest).selectExpr("start", "walk_no", "planned_len", "step", "node")


@query(f"{_sampled()} SELECT CAST(planned_len AS INTEGER) AS planned_len, count(*) AS walks FROM planned GROUP BY planned_len")
def walk_length_histogram(spark, d):
    g = _pages(spark, d)
    return walks.planned(g, _planned_of(g), SEED).groupBy("planned_len").agg(F.count(F.lit(1)).alias("walks"))


def _decaying(per_node: str, most: str) -> str:
    u = f"({draw_sql(SEED, 'length', 'id', 'walk_no')} + 0.5) / {float(SPAN)}"
    return f"planned AS (SELECT id AS start, walk_no, least(CAST(floor(ln({u}) / ln(sqrt(CAST({C} AS DOUBLE)))) AS INTEGER), {most}) AS planned_len FROM nodes, range(1, 1 + {per_node}) t(walk_no))"


@query(f"WITH {_PAGES}, {_ADJ}, {_decaying('40', '1000')} SELECT planned_len, count(*) AS walks FROM planned GROUP BY planned_len")
def decay_walk_lengths(spark, d):
    return walks.decaying(_pages(spark, d), 40, C, SEED).groupBy("planned_len").agg(F.count(F.lit(1)).alias("walks"))


def _warm(per_node: str, most: str, source: str) -> str:
    return f"""WITH RECURSIVE {_PAGES}, {_ADJ}, {_N}, {_decaying(per_node, most)}, {_walks()}, src AS (SELECT CAST({source} AS BIGINT) AS id),
    met AS (SELECT DISTINCT s.start AS source, t.start AS node, t.walk_no FROM steps t JOIN steps s USING (walk_no, step, node) JOIN src ON s.start = src.id WHERE t.start <> s.start)"""


_WARM_N = "(SELECT CAST(ceil(ln(2.0 * n * n) / (2 * pow(0.3, 2))) AS BIGINT) FROM n)"


@query(f"""{_warm(_WARM_N, f"(SELECT CAST(ceil(3 * ln(n / CAST(0.3 AS DOUBLE)) / ln(1 / sqrt(CAST({C} AS DOUBLE)))) AS INTEGER) FROM n)", str(SOURCE))}
    SELECT source, node, round(count(*) / CAST({_WARM_N} AS DOUBLE), 9) AS score FROM met GROUP BY 1, 2 UNION ALL SELECT id, id, 1.0 FROM src""")
def warmup_scores(spark, d):
    return rounded(simrank.warm_up(_pages(spark, d), SOURCE, C, 0.3, SEED, strategy="local"), "score")


_COIN_N = "(SELECT CAST(ceil(ln(2.0 * n * n) / (2 * pow(0.3, 2))) AS BIGINT) FROM n)"
_COIN_MOST = f"(SELECT CAST(ceil(3 * ln(n / CAST(0.3 AS DOUBLE)) / ln(1 / sqrt(CAST({C} AS DOUBLE)))) AS INTEGER) FROM n)"


@query(f"""WITH RECURSIVE {_TRADE.format(300000)}, {_ADJ}, {_N}, src AS (SELECT min(id) AS id FROM nodes),
    planned AS (SELECT id AS start, walk_no, {_COIN_MOST} AS planned_len FROM nodes, range(1, 1 + {_COIN_N}) t(walk_no)),
    {_walks().replace("WHERE w.step < w.planned_len", f"WHERE {draw_sql(SEED, 'coin', 'w.start', 'w.walk_no', 'w.step + 1')} < {int(math.sqrt(C) * SPAN)} AND w.step < w.planned_len")},
    met AS (SELECT DISTINCT s.start AS source, t.start AS node, t.walk_no FROM steps t JOIN steps s USING (walk_no, step, node) JOIN src ON s.start = src.id WHERE t.start <> s.start)
    SELECT source, node, round(count(*) / CAST({_COIN_N} AS DOUBLE), 9) AS score FROM met GROUP BY 1, 2 UNION ALL SELECT id, id, 1.0 FROM src""")
def warmup_scores_per_step_coin(spark, d):
    g = graphs.from_edges(workloads.nation_trade(spark, d).edges)
    first = g.nodes.agg(F.min("id")).first()[0]
    return rounded(simrank.warm_up(g, first, C, 0.3, SEED, coin="per_step"), "score")


@query(f"""{_warm('500', '60', '1').replace("FROM nodes, range(1,", "FROM (SELECT unnest([1, 3]) AS id) nodes2, range(1,")}
    SELECT count(*) AS hits, 500 AS pairs, round(count(*) / 500.0, 9) AS score, {round(bounds.half_width(500, 0.05), 9)} AS half_width FROM met WHERE node = 3""")
def pair_monte_carlo(spark, d):
    return rounded(pairs.monte_carlo(_pages(spark, d), 1, 3, 500, C, SEED), "score", "half_width")


@query()
def independent_pairs_scores(spark, d):
    g = graphs.from_edges(workloads.nation_trade(spark, d).edges)
    first = g.nodes.agg(F.min("id")).first()[0]
    return rounded(pairs.independent_pairs(g, first, 200, C, SEED), "score")


_LABELS_OUT = "SELECT start, CAST(walk_no AS INTEGER) AS walk_no, CAST(pair AS INTEGER) AS pair FROM labels"


@query(f"{_sampled()} {_LABELS_OUT}")
def walk_labels_window(spark, d):
    g = _pages(spark, d)
    return walks.labels(walks.planned(g, _planned_of(g), SEED), SEED, "window")


@query(f"{_sampled()} {_LABELS_OUT}")
def walk_labels_pre_permuted(spark, d):
    g = _pages(spark, d)
    return walks.pre_permuted(g, _planned_of(g), SEED).select("start", "walk_no", "pair")


@query(f"""{_sampled()} SELECT start, CAST(walk_no AS INTEGER) AS walk_no, CAST(pair AS INTEGER) AS pair FROM labels""")
def walk_labels_boundary_swap(spark, d):
    """Groups that sorting splits are made whole by moving them, then ranked."""
    g = _pages(spark, d)
    walkers = walks.planned(g, _planned_of(g), SEED).select("start", "walk_no")
    order = F.struct(walks.draw(SEED, "perm", F.col("start"), F.col("walk_no")), F.col("walk_no"))
    return primitives.swap_shuffle(walkers, "start", order).select("start", "walk_no", "pair")


@query(f"{_sampled()} SELECT CAST(pair AS INTEGER) AS pair, CAST(step AS INTEGER) AS step, node, CAST(walk_len AS INTEGER) AS walk_len, start FROM tuples")
def walk_tuples(spark, d):
    g = _pages(spark, d)
    return simrank.labelled_tuples(g, _planned_of(g), SEED, "local")


@query(f"{_sampled()} SELECT CAST(pair AS INTEGER) AS pair, CAST(step AS INTEGER) AS step, node, CAST(walk_len AS INTEGER) AS walk_len, start FROM tuples")
def walk_tuples_from_paths(spark, d):
    g = _pages(spark, d)
    plan = _planned_of(g)
    whole = walks.paths(walks.generate(g, plan, SEED, "local")).join(walks.pre_permuted(g, plan, SEED).select("start", "walk_no", "pair"), ["start", "walk_no"])
    return walks.decompose(whole)


# --- meetings and scores ------------------------------------------------------------------------

_MEETS_OUT = f"{_sampled()}, {_MEETS} SELECT CAST(pair AS INTEGER) AS pair, source, CAST(source_len AS INTEGER) AS source_len, target, CAST(target_len AS INTEGER) AS target_len FROM meets"


def _meeting_tuples(g, plan, sources=(SOURCE,)):
    """Tuples of all walks that can meet the sources' walks."""
    adj = walks.prepared(g)
    return simrank.labelled_tuples(g, plan, SEED, "local", adj=adj, starts=simrank.starts_of(g, list(sources), plan.longest, adj))


def _meets_query(name: str, method: str):
    def run(spark, d):
        g = _pages(spark, d)
        plan = _planned_of(g)
        if method == "fused":
            adj = walks.prepared(g)
            return simrank.fused_meets(g, plan, SOURCE, SEED, adj, simrank.starts_of(g, [SOURCE], plan.longest, adj)).select(*meeting.MEETS)
        return meeting.detect(_meeting_tuples(g, plan), SOURCE, method)

    run.__name__ = name
    query(_MEETS_OUT)(run)


for _m in ("broadcast_join", "predecessor", "global_predecessor", "fused"):
    _meets_query(f"meets_{_m}", _m)

_SCORES_OUT = "SELECT source, node, round(score, 9) AS score FROM scores"


def _scores_query(name: str, normalization: str, method: str = "broadcast_join", oracle: bool = True, sql_how: dict | None = None, **how):
    def run(spark, d):
        scores = simrank.single_source(_pages(spark, d), SOURCE, C, EPS, SEED, normalization=normalization, strategy="local", method=method, **how)
        return rounded(scores, "score")

    run.__name__ = name
    query(f"{_sampled(**(sql_how or {}))}, {_scores(normalization)} {_SCORES_OUT}" if oracle else None)(run)


for _n in ("ideal", "unbiased", "plain"):
    _scores_query(f"scores_{_n}", _n)
_scores_query("scores_fused", "ideal", method="fused")
_scores_query("scores_clip", "unbiased", truncation="clip", sql_how={"clip": True})
_scores_query("scores_all_nodes_scope", "ideal", scope="all_nodes", sql_how={"scope": "n * n"})
_scores_query("scores_bernoulli", "unbiased", rounding="bernoulli", oracle=False)


@query(f"{_sampled().replace('row_number() OVER (PARTITION BY start ORDER BY ' + draw_sql(SEED, 'perm', 'start', 'walk_no') + ', walk_no)', 'walk_no')}, {_scores('ideal')} {_SCORES_OUT}")
def scores_without_shuffle(spark, d):
    """Control: pairs in the order of lengths."""
    return rounded(simrank.single_source(_pages(spark, d), SOURCE, C, EPS, SEED, strategy="local", labels="none", method="broadcast_join"), "score")


@query(f"{_sampled()}, {_MEETS.replace('SELECT DISTINCT', 'SELECT')}, total AS (SELECT sum(actual) AS total FROM plan) SELECT source, target AS node, round(sum(ps.ideal / ps.actual * pt.ideal / pt.actual / z), 9) AS score FROM meets JOIN plan ps ON ps.len = source_len JOIN plan pt ON pt.len = target_len, const GROUP BY source, target")
def scores_counted_per_tuple(spark, d):
    """Control: every meeting of a pair counts, not the pair once."""
    g = _pages(spark, d)
    plan = _planned_of(g)
    return rounded(meeting.aggregate(meeting.by_join(_meeting_tuples(g, plan), SOURCE, once=False), plan), "score")


@query(f"{_sampled()}, {_scores('ideal')} SELECT source, node, round(score, 9) AS score FROM scores WHERE source <> node ORDER BY scores.score DESC, node LIMIT 10")
def top_k_similar_pages(spark, d):
    return rounded(simrank.top_k(simrank.single_source(_pages(spark, d), SOURCE, C, EPS, SEED), 10), "score")


@query(f"{_sampled()}, {_scores('ideal')} SELECT source, node, round(score, 9) AS score FROM scores WHERE source <> node AND score >= 0.05")
def scores_threshold(spark, d):
    return rounded(simrank.at_least(simrank.single_source(_pages(spark, d), SOURCE, C, EPS, SEED), 0.05), "score")


_MANY = _sampled().replace(f"src AS (SELECT CAST({SOURCE} AS BIGINT) AS id)", "src AS (SELECT CAST(unnest([1, 3, 5]) AS BIGINT) AS id)")


def _many(spark, d):
    g = _pages(spark, d)
    plan = _planned_of(g)
    ids = spark.createDataFrame([(1,), (3,), (5,)], "id long")
    return simrank.multi_source(g, ids, plan, SEED, tuples=_meeting_tuples(g, plan, (1, 3, 5)))


@query(f"{_MANY}, {_scores('ideal')} {_SCORES_OUT}")
def multi_source_scores(spark, d):
    return rounded(_many(spark, d), "score")


@query(f"{_MANY}, {_scores('ideal')} SELECT source, node, round(score, 9) AS score, CAST(rank AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY score DESC, node) AS rank FROM scores WHERE source <> node) WHERE rank <= 5")
def top_k_per_source(spark, d):
    return rounded(simrank.top_k_per_source(_many(spark, d), 5), "score")


@query(f"{_MANY}, {_scores('ideal')} SELECT node, arg_max(source, (score, -source)) AS seed, round(max(score), 9) AS score FROM scores GROUP BY node")
def assign_to_seeds(spark, d):
    return rounded(simrank.assign_to_seeds(_many(spark, d)), "score")


@query(f"{_sampled()}, {_scores('ideal')} {_SCORES_OUT}")
def walk_index_query(spark, d):
    import uuid

    g = _pages(spark, d)
    built = index.WalkIndex.build(g, _planned_of(g), f"{tables.shared_folder(spark)}/index-{uuid.uuid4().hex}", SEED, "local")
    return rounded(built.query(SOURCE), "score")


@query()
def scores_stitched(spark, d):
    g = _pages(spark, d)
    return rounded(simrank.single_source(g, SOURCE, C, EPS, SEED, strategy="stitched", method="broadcast_join"), "score")


@query()
def stitched_shortfall_by_slack(spark, d):
    """On a graph that grows with the tables."""
    g = _pages(spark, d)
    plan, adj, out = _planned_of(g, eps=0.2), walks.prepared(g), None
    for slack, reuse in ((1.0, False), (1.5, False), (1.0, True)):
        short = stitched(g, plan, walks.planned(g, plan, SEED), adj, SEED, Supply(4, slack, 0.0, reuse))[1]
        part = short.select(F.lit(slack).alias("slack"), F.lit(reuse).alias("reuse"), "level", "missing")
        out = part if out is None else out.union(part)
    return out


# --- accuracy and cost --------------------------------------------------------------------------


@query(f"{_sampled()}, {_exact(5)}, {_scores('ideal')}, j AS (SELECT coalesce(e.node, x.b) AS node, coalesce(e.score, 0) AS est, coalesce(x.score, 0) AS exact FROM (SELECT node, score FROM scores) e FULL JOIN (SELECT b, score FROM s5 JOIN src ON a = id) x ON e.node = x.b WHERE coalesce(e.node, x.b) <> {SOURCE}) SELECT CAST({SOURCE} AS BIGINT) AS source, round(max(abs(est - exact)), 9) AS max_abs_error FROM j")
def error_vs_exact(spark, d):
    g = _pages(spark, d)
    est = simrank.single_source(g, SOURCE, C, EPS, SEED)
    return rounded(metrics.max_abs_error(est, exact.single_source(g, SOURCE, C, 5)), "max_abs_error")


@query()
def error_summary_by_method(spark, d):
    """Every method on the undirected page graph, against the exact scores: rows of the comparison."""
    g = _pages(spark, d)
    truth = tables.keep(exact.single_source(g, SOURCE, C, 10), "truth")
    runs = {
        "fixed_length": simrank.single_source(g, SOURCE, C, 0.1, SEED),
        "fixed_length_unbiased": simrank.single_source(g, SOURCE, C, 0.1, SEED, normalization="unbiased"),
        "warm_up": simrank.warm_up(g, SOURCE, C, 0.2, SEED, strategy="local"),
        "unidirectional": baselines.unidirectional(g, SOURCE, C, 6, 3000, SEED),
        "linear_constant_diagonal": baselines.linear_jacobi(g, SOURCE, C, 8, diagonal="constant"),
        "linear_jacobi": baselines.linear_jacobi(g, SOURCE, C, 8, jacobi_iters=4, eps_p=0.1, seed=SEED),
        "linear_forest": baselines.linear_forest(g, SOURCE, C, 8, seed=SEED, pairs=200),
        "linear_pair_diagonal": baselines.linear_forest(g, SOURCE, C, 8, eps_d=0.2, diagonal="pair_mc", seed=SEED),
        "linear_exact_diagonal": baselines.linear_forest(g, SOURCE, C, 8, diagonal="exact"),
        "zero": truth.filter(F.lit(False)),
    }
    out = None
    for name, est in runs.items():
        part = metrics.error_summary(est, truth).select(F.lit(name).alias("method"), "n", "max_abs_error", "mean_abs_error", "bias")
        out = part if out is None else out.union(part)
    return rounded(out, "max_abs_error", "mean_abs_error", "bias")


@query()
def failure_rate_over_seeds(spark, d):
    g = graphs.from_edges(workloads.nation_trade(spark, d).edges)
    first = g.nodes.agg(F.min("id")).first()[0]
    truth = tables.keep(exact.single_source(g, first, C, 12), "truth")
    return metrics.failure_rate(lambda s: simrank.single_source(g, first, C, 0.25, s, strategy="local", method="broadcast_join"), truth, [1, 2, 3], 0.25)


@query()
def ranking_vs_exact(spark, d):
    g = _pages(spark, d)
    est = simrank.single_source(g, SOURCE, C, 0.1, SEED)
    return rounded(metrics.ranking(est, exact.single_source(g, SOURCE, C, 6), 10), "precision", "ndcg", "kendall_tau")


@query()
def expected_estimates(spark, d):
    g = graphs.from_edges(workloads.nation_trade(spark, d).edges)
    first = g.nodes.agg(F.min("id")).first()[0]
    plan, out = _planned_of(g), None
    for how in ("ideal", "unbiased", "plain"):
        part = exact.expected_estimate(g, first, plan, how).select(F.lit(how).alias("normalization"), "source", "node", "score")
        out = part if out is None else out.union(part)
    return rounded(out, "score")


@query(f"{_sampled()}, raw AS (SELECT t.pair, s.start AS source, t.start AS target FROM tuples t JOIN tuples s USING (pair, step, node) JOIN src ON s.start = src.id WHERE t.start <> s.start), per AS (SELECT count(*) AS n FROM raw GROUP BY pair, source, target) SELECT CAST(sum(n) AS BIGINT) AS raw, count(*) AS unique, max(n) AS most FROM per")
def messages_per_walk(spark, d):
    g = _pages(spark, d)
    return metrics.messages_per_walk(meeting.by_join(_meeting_tuples(g, _planned_of(g)), SOURCE, once=False))


@query()
def ledger_rounds_by_strategy(spark, d):
    """Exchanges, rows and bytes that ran for each way to walk and to detect meetings."""
    g = _pages(spark, d)
    plan = _planned_of(g)
    adj = walks.prepared(g)
    book = ledger.Ledger(spark, plan.n)
    for name in ("local", "stepwise", "stitched"):
        book.measure(name, "walks", lambda name=name: walks.generate(g, plan, SEED, name, adj=adj))
    t = simrank.labelled_tuples(g, plan, SEED, "local", adj=adj)
    for name in meeting.METHODS:
        book.measure(name, "meetings", lambda name=name: meeting.detect(t, SOURCE, name))
    return book.frame()


@query()
def rounds_by_size(spark, d):
    """Exchanges of walking against the number of nodes and the longest length, on three graphs."""
    book = ledger.Ledger(spark)
    for name, g in (("nation_trade", _trade(spark, d)[0]), ("user_transition", workloads.user_transition(spark, d, end="2024-01-02")), ("page_links", _pages(spark, d))):
        plan, adj = _planned_of(g, eps=0.3), walks.prepared(g)
        for strategy in ("local", "stepwise", "stitched"):
            book.measure(strategy, f"{name}: {plan.n} nodes, longest {plan.longest}", lambda: walks.generate(g, plan, SEED, strategy, adj=adj))
    return book.frame()


@query()
def comparison_of_methods(spark, d):
    """Every method at one eps on the undirected page graph: what ran, and the error of its scores. The
    ranked adjacency is prepared before and counts for none."""
    g, eps = _pages(spark, d), 0.2
    walks.prepared(g)
    truth = tables.keep(exact.single_source(g, SOURCE, C, 10), "truth")
    runs = {
        "fixed_length": lambda: simrank.single_source(g, SOURCE, C, eps, SEED, normalization="unbiased"),
        "fixed_length_stitched": lambda: simrank.single_source(g, SOURCE, C, eps, SEED, normalization="unbiased", strategy="stitched", method="broadcast_join"),
        "warm_up": lambda: simrank.warm_up(g, SOURCE, C, eps, SEED),
        "linear_jacobi": lambda: baselines.linear_jacobi(g, SOURCE, C, 8, jacobi_iters=4, eps_p=eps, seed=SEED),
        "unidirectional": lambda: baselines.unidirectional(g, SOURCE, C, 6, math.ceil(bounds.warm_up_walks(g.size(), eps)), SEED),
        "linear_forest": lambda: baselines.linear_forest(g, SOURCE, C, 8, eps_d=eps, seed=SEED),
        "exact": lambda: exact.single_source(g, SOURCE, C, 10),
    }
    book, out = ledger.Ledger(spark, g.size()), None
    for name, run in runs.items():
        est = book.measure(name, f"eps {eps}", run)
        part = metrics.error_summary(est, truth).select(F.lit(name).alias("method"), "max_abs_error", "mean_abs_error", "bias")
        out = part if out is None else out.union(part)
    return book.frame().join(out, "method")


@query()
def error_by_eps_and_c(spark, d):
    """Error and walks of a node as eps and c move, on the undirected page graph."""
    g, out = _pages(spark, d), None
    for c, eps in ((0.6, 0.3), (0.6, 0.2), (0.6, 0.1), (0.4, 0.2), (0.8, 0.2)):
        truth = exact.single_source(g, SOURCE, c, 12)
        est = simrank.single_source(g, SOURCE, c, eps, SEED, normalization="unbiased", strategy="local", method="broadcast_join")
        plan = SamplingPlan.create(g.size(), c, eps)
        part = metrics.error_summary(est, truth).select(F.lit(c).alias("c"), F.lit(eps).alias("eps"), F.lit(plan.total).alias("walks"), F.lit(plan.steps).alias("steps"), "max_abs_error", "mean_abs_error", "bias")
        part = tables.keep(part, "error")
        out = part if out is None else out.union(part)
    return rounded(out, "max_abs_error", "mean_abs_error", "bias")


@query()
def max_partition_rows(spark, d):
    """The widest task when edges are dealt by node (arrays) and by (node, rank)."""
    g = _pages(spark, d)
    adj = walks.prepared(g)
    widest = lambda df: metrics.partition_sizes(df).agg(F.max("rows")).first()[0]
    return spark.createDataFrame([("by node", widest(adj.repartition(32, "node"))), ("by node and rank", widest(adj.repartition(32, "node", "rk")))], "layout string, rows long")


# --- baselines ----------------------------------------------------------------------------------


def _linear(terms: int, diag: str) -> str:
    """Scores of the linear form over p(node, nbr, p) with diag(node, d)."""
    parts = [diag, "m0 AS (SELECT id AS node, CAST(1 AS DOUBLE) AS m FROM src)"]
    parts += [f"m{t} AS (SELECT nbr AS node, sum(m * p) AS m FROM m{t - 1} m JOIN p ON p.node = m.node GROUP BY nbr)" for t in range(1, terms + 1)]
    parts.append(f"y{terms} AS (SELECT node, m * d AS m FROM m{terms} JOIN diag USING (node))")
    for t in range(terms - 1, -1, -1):
        parts.append(f"y{t} AS (SELECT node, sum(m) AS m FROM (SELECT p.node, {C} * m * p AS m FROM y{t + 1} y JOIN p ON p.nbr = y.node UNION ALL SELECT node, m * d FROM m{t} JOIN diag USING (node)) GROUP BY node)")
    return ", ".join(parts)


_TRADE_ALL = f"{_TRADE.format(300000)}, {_EDGE_NODES}, {_exact(0)}, src AS (SELECT min(id) AS id FROM nodes)"
_LINEAR_OUT = "SELECT id AS source, node, round(m, 9) AS score FROM y0, src WHERE node <> id UNION ALL SELECT id, id, 1.0 FROM src"


def _trade(spark, d):
    g = graphs.from_edges(workloads.nation_trade(spark, d).edges)
    return g, g.nodes.agg(F.min("id")).first()[0]


@query(f"WITH {_TRADE_ALL}, {_linear(6, f'diag AS (SELECT id AS node, CAST({1.0 - C} AS DOUBLE) AS d FROM nodes)')} {_LINEAR_OUT}")
def baseline_linear_constant_diagonal(spark, d):
    g, first = _trade(spark, d)
    return rounded(baselines.linear_jacobi(g, first, C, 6, diagonal="constant"), "score")


def _sweeps_sql(sweeps: int) -> str:
    """diag by sweeps over the system a(i, k, a)."""
    parts = [f"d0 AS (SELECT id AS node, CAST({1.0 - C} AS DOUBLE) AS d FROM nodes)"]
    parts += [f"d{s} AS (SELECT o.i AS node, (1 - coalesce(r.rest, 0)) / o.a AS d FROM a o LEFT JOIN (SELECT a.i, sum(a.a * x.d) AS rest FROM a JOIN d{s - 1} x ON x.node = a.k WHERE a.i <> a.k GROUP BY a.i) r ON r.i = o.i WHERE o.i = o.k)" for s in range(1, sweeps + 1)]
    return ", ".join([*parts, f"diag AS (SELECT node, d FROM d{sweeps})"])


def _jacobi_sql(length: int, sweeps: int) -> str:
    parts = ["r0 AS (SELECT id AS i, id AS k, CAST(1 AS DOUBLE) AS m FROM nodes)"]
    parts += [f"r{t} AS (SELECT i, nbr AS k, sum(m * p) AS m FROM r{t - 1} r JOIN p ON p.node = r.k GROUP BY 1, 2)" for t in range(1, length + 1)]
    parts.append("a AS (SELECT i, k, sum(a) AS a FROM (" + " UNION ALL ".join(f"SELECT i, k, m * m * pow(CAST({C} AS DOUBLE), {t}) AS a FROM r{t}" for t in range(length + 1)) + ") GROUP BY i, k)")
    parts.append(f"d0 AS (SELECT id AS node, CAST({1.0 - C} AS DOUBLE) AS d FROM nodes)")
    parts += [f"d{s} AS (SELECT o.i AS node, (1 - coalesce((SELECT sum(a.a * x.d) FROM a JOIN d{s - 1} x ON x.node = a.k WHERE a.i = o.i AND a.k <> o.i), 0)) / o.a AS d FROM a o WHERE o.i = o.k)" for s in range(1, sweeps + 1)]
    parts.append(f"diag AS (SELECT node, d FROM d{sweeps})")
    return ", ".join(parts)


@query(f"WITH {_TRADE_ALL}, {_linear(5, _jacobi_sql(5, 4))} {_LINEAR_OUT}")
def baseline_linear_jacobi_exact_rows(spark, d):
    g, first = _trade(spark, d)
    return rounded(baselines.linear_jacobi(g, first, C, 5, jacobi_iters=4, rows="exact"), "score")


def _walkers(per_node: str, length: str, doubled: bool = False) -> str:
    """planned(start, walk_no, planned_len): ``per_node`` walks of every node."""
    return f"planned AS (SELECT id AS start, walk_no, {length} AS planned_len FROM nodes, range(1, 1 + {'2 * ' * doubled}{per_node}) t(walk_no))"


def _trade_walks(planned: str, rest: str, tree: bool = False) -> str:
    """Walks of the trade graph, then ``rest``, then the linear form's scores."""
    walked = _walks()
    if tree:
        walked = walked.replace(draw_sql(SEED, "step", "w.start", "w.walk_no", "w.step + 1"), draw_sql(SEED, "tree", "w.node", "w.walk_no", "w.step + 1"))
    return f"WITH RECURSIVE {_TRADE.format(300000)}, {_ADJ}, {_N}, p AS (SELECT node, nbr, 1.0 / node_deg AS p FROM adj), src AS (SELECT min(id) AS id FROM nodes), {planned}, {walked}, {rest} {_LINEAR_OUT}"


_ROWS_N = "(SELECT CAST(ceil(ln(2.0 * n * n) / (2 * pow(0.1, 2))) AS BIGINT) FROM n)"
_PAIRS_N = "(SELECT CAST(ceil(ln(2.0 * n * n) / (2 * pow(0.2, 2))) AS BIGINT) FROM n)"
_PAIRS_LEN = f"least(CAST(floor(ln(({draw_sql(SEED, 'length', 'id', 'walk_no')} + 0.5) / {float(SPAN)}) / ln(sqrt(CAST({C} AS DOUBLE)))) AS INTEGER), (SELECT CAST(ceil(ln(n / CAST(0.2 AS DOUBLE)) / ln(1 / sqrt(CAST({C} AS DOUBLE)))) AS INTEGER) FROM n))"
_COUNTED_ROWS = f"""seen AS (SELECT start AS i, step, node AS k, count(*) / CAST({_ROWS_N} AS DOUBLE) AS m FROM steps GROUP BY 1, 2, 3),
    a AS (SELECT i, k, sum(a) AS a FROM (SELECT id AS i, id AS k, CAST(1 AS DOUBLE) AS a FROM nodes UNION ALL SELECT i, k, m * m * pow(CAST({C} AS DOUBLE), step) FROM seen) GROUP BY i, k)"""
_MET_DIAGONAL = f"""met AS (SELECT DISTINCT x.start, x.walk_no FROM steps x JOIN steps y ON y.start = x.start AND y.walk_no = x.walk_no + 1 AND y.step = x.step AND y.node = x.node WHERE x.walk_no % 2 = 1),
    diag AS (SELECT id AS node, 1 - count(met.start) / CAST({_PAIRS_N} AS DOUBLE) AS d FROM nodes LEFT JOIN met ON met.start = id GROUP BY id)"""


@query(_trade_walks(_walkers(_ROWS_N, "5"), f"{_COUNTED_ROWS}, {_linear(5, _sweeps_sql(4))}"))
def baseline_linear_jacobi(spark, d):
    g, first = _trade(spark, d)
    return rounded(baselines.linear_jacobi(g, first, C, 5, rows_per_batch=10, jacobi_iters=4, eps_p=0.1, seed=SEED), "score")


@query(f"""WITH RECURSIVE {_PAGES}, {_ADJ}, src AS (SELECT CAST({SOURCE} AS BIGINT) AS id), planned AS (SELECT id AS start, walk_no, 10 AS planned_len FROM src, range(1, 2001) t(walk_no)), {_walks()},
    stood AS (SELECT walk_no, step, node FROM w), ends AS (SELECT e.walk_no, CAST(e.step / 2 AS BIGINT) AS t, m.node AS mid, e.node FROM stood e JOIN stood m ON m.walk_no = e.walk_no AND 2 * m.step = e.step WHERE e.step > 0),
    early AS (SELECT DISTINCT e.walk_no, e.t FROM ends e JOIN stood x ON x.walk_no = e.walk_no AND x.step < e.t JOIN stood y ON y.walk_no = e.walk_no AND y.step = 2 * e.t - x.step AND y.node = x.node)
    SELECT CAST({SOURCE} AS BIGINT) AS source, q.node, round(sum(pow(CAST({C} AS DOUBLE), t) * dm.deg / dn.deg) / 2000, 9) AS score FROM (SELECT ends.* FROM ends ANTI JOIN early USING (walk_no, t)) q JOIN degree dm ON dm.node = q.mid JOIN degree dn ON dn.node = q.node
    WHERE q.node <> {SOURCE} GROUP BY q.node UNION ALL SELECT id, id, 1.0 FROM src""")
def baseline_unidirectional(spark, d):
    return rounded(baselines.unidirectional(_pages(spark, d), SOURCE, C, 5, 2000, SEED), "score")


@query(_trade_walks(_walkers(_PAIRS_N, _PAIRS_LEN, True), _linear(8, _MET_DIAGONAL), tree=True))
def baseline_linear_forest(spark, d):
    g, first = _trade(spark, d)
    return rounded(baselines.linear_forest(g, first, C, 8, eps_d=0.2, seed=SEED), "score")


@query(_trade_walks(_walkers(_PAIRS_N, _PAIRS_LEN, True), _linear(8, _MET_DIAGONAL)))
def baseline_linear_pair_diagonal(spark, d):
    g, first = _trade(spark, d)
    return rounded(baselines.linear_forest(g, first, C, 8, eps_d=0.2, diagonal="pair_mc", seed=SEED), "score")


_EXACT_ROWS = _jacobi_sql(6, 1).split(", d0 AS")[0]


@query(f"WITH {_TRADE_ALL}, {_linear(6, f'{_EXACT_ROWS}, {_sweeps_sql(30)}')} {_LINEAR_OUT}")
def baseline_linear_exact_diagonal(spark, d):
    g, first = _trade(spark, d)
    return rounded(baselines.linear_forest(g, first, C, 6, diagonal="exact"), "score")


# --- reports ------------------------------------------------------------------------------------

_RUNS = "r AS (SELECT 'links' AS graph, CASE WHEN node % 2 = 0 THEN 'page' ELSE 'target' END AS kind, score FROM scores WHERE source <> node)"


def _runs(spark, d):
    s = simrank.single_source(_pages(spark, d), SOURCE, C, EPS, SEED, normalization="plain", strategy="local", method="broadcast_join")
    return s.filter("source != node").select(F.lit("links").alias("graph"), F.when(F.col("node") % 2 == 0, "page").otherwise("target").alias("kind"), "score")


def _report_query(name: str, clause: str, mode: str, sets=None):
    def run(spark, d):
        return rounded(metrics.report(_runs(spark, d), ["graph", "kind"], "score", mode, sets), "mean")

    run.__name__ = name
    query(f"{_sampled()}, {_scores('plain')}, {_RUNS} SELECT graph, kind, count(*) AS n, round(avg(score), 9) AS mean FROM r GROUP BY {clause}")(run)


_report_query("report_rollup", "ROLLUP (graph, kind)", "rollup")
_report_query("report_cube", "CUBE (graph, kind)", "cube")
_report_query("report_grouping_sets", "GROUPING SETS ((graph), (kind))", "sets", [["graph"], ["kind"]])


@query(f"WITH {_LINKS}, o AS (SELECT DISTINCT src AS id FROM directed), a AS (SELECT src, dst FROM directed WHERE dst <= 101), b AS (SELECT src, dst FROM directed WHERE dst >= 51) SELECT 'both' AS kind, src, dst FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'first only', src, dst FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'any', src, dst FROM (SELECT * FROM a UNION SELECT * FROM b)")
def graph_set_operations(spark, d):
    g = workloads.page_links(spark, d)
    a, b = graphs.Graph(g.nodes, g.edges.filter("dst <= 101")), graphs.Graph(g.nodes, g.edges.filter("dst >= 51"))
    out = None
    for kind, x in (("both", graphs.intersect(a, b)), ("first only", graphs.subtract(a, b)), ("any", graphs.union(a, b))):
        part = x.edges.select(F.lit(kind).alias("kind"), "src", "dst")
        out = part if out is None else out.union(part)
    return out


@query(f"WITH {_PAGES}, {_ADJ}, {_plan()} SELECT CAST(len AS INTEGER) AS len, round(ideal, 6) AS ideal, CAST(actual AS INTEGER) AS actual FROM plan")
def length_plan_table_function(spark, d):
    sql.register_functions(spark)
    n = _pages(spark, d).size()
    return rounded(spark.sql(f"SELECT * FROM length_plan({n}, CAST({C} AS DOUBLE), CAST({EPS} AS DOUBLE))"), "ideal", digits=6)


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten nodes most similar to the source, by the fixed-length-plan method."""
    return simrank.top_k(simrank.single_source(_pages(spark, sf_dir), SOURCE, C, EPS, SEED, strategy="local", method="broadcast_join"), 10)
