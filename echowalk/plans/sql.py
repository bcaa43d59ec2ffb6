"""SQL surface: views of tables and graphs, table functions, scores as views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.sampling import SamplingPlan
from ..sources.graphs import Graph, ranked_adjacency
from ..sources.tables import TABLES, keep, read


def register_views(spark: SparkSession, sf_dir: str, names=TABLES) -> None:
    for n in names:
        read(spark, sf_dir, n).createOrReplaceTempView(n)


def register_graph(g: Graph, name: str = "graph") -> None:
    """Views <name>_nodes, <name>_edges and <name>_adj."""
    g.nodes.createOrReplaceTempView(f"{name}_nodes")
    g.edges.createOrReplaceTempView(f"{name}_edges")
    keep(ranked_adjacency(g), "adjacency").createOrReplaceTempView(f"{name}_adj")


class LengthPlan:
    """length_plan(n, c, eps): rows len, ideal, actual."""

    def eval(self, n: int, c: float, eps: float):
        plan = SamplingPlan.create(int(n), float(c), float(eps))
        for i, (x, k) in enumerate(zip(plan.ideal, plan.actual)):
            yield i, x, k


class DecomposeWalk:
    """decompose_walk(path): rows step, node after the start."""

    def eval(self, path):
        for k, node in enumerate(path or ()):
            yield k + 1, node


def register_functions(spark: SparkSession) -> None:
    spark.udtf.register("length_plan", F.udtf(LengthPlan, returnType="len int, ideal double, actual int"))
    spark.udtf.register("decompose_walk", F.udtf(DecomposeWalk, returnType="step int, node long"))


def recursive_walks(spark: SparkSession, adj: str, walkers: str, seed: int, longest: int) -> DataFrame:
    """The walks of view ``walkers`` (start, walk_no, planned_len, deg) over view ``adj``, in one
    recursive query; the same rows as the stepwise walker."""
    hash_of = f"CAST(conv(substring(md5(concat_ws('|', '{seed}', 'step', CAST(w.start AS STRING), CAST(w.walk_no AS STRING), CAST(w.step + 1 AS STRING))), 1, 8), 16, 10) AS BIGINT)"
    return spark.sql(f"""
        WITH RECURSIVE w(start, walk_no, planned_len, step, node, deg) MAX RECURSION LEVEL {longest + 2} AS (
            SELECT start, walk_no, planned_len, 0, start, deg FROM {walkers}
            UNION ALL
            SELECT w.start, w.walk_no, w.planned_len, w.step + 1, a.nbr, a.nbr_deg
            FROM w JOIN {adj} a ON a.node = w.node AND a.rk = CAST({hash_of} % w.deg AS INT)
            WHERE w.step < w.planned_len AND w.deg > 0)
        SELECT start, walk_no, planned_len, step, node FROM w WHERE step > 0""")
