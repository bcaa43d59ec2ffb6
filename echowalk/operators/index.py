"""Walks do not depend on the source: an index keeps them for many queries."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.sampling import SamplingPlan
from ..sources.graphs import Graph
from ..sources.tables import write_index
from . import meeting


class WalkIndex:
    """Tuples in Parquet, by step; the plan is kept beside them."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path
        said = json.loads(spark.read.json(f"{path}/plan").select(F.to_json(F.struct("*"))).first()[0])
        self.plan = SamplingPlan(**{k: tuple(v) if isinstance(v, list) else v for k, v in said.items()})

    @classmethod
    def build(cls, g: Graph, plan: SamplingPlan, path: str, seed: int = 0, strategy: str = "stepwise") -> WalkIndex:
        from ..plans.simrank import labelled_tuples

        spark = g.edges.sparkSession
        write_index(labelled_tuples(g, plan, seed, strategy), f"{path}/tuples")
        spark.createDataFrame([(json.dumps(plan.__dict__),)], "value string").write.text(f"{path}/plan")
        return cls(spark, path)

    def tuples(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/tuples").select("pair", F.col("step").cast("int").alias("step"), "node", "walk_len", "start")

    def query(self, source: int, normalization: str = "ideal") -> DataFrame:
        """Steps beyond the source's longest walk are not read."""
        from ..plans.simrank import finish

        all_tuples = self.tuples()
        most = all_tuples.filter(F.col("start") == source).agg(F.max("step")).first()[0] or 0
        return finish(meeting.aggregate(meeting.by_join(all_tuples.filter(F.col("step") <= most), source), self.plan, normalization), source)

    def query_many(self, sources: DataFrame, normalization: str = "ideal") -> DataFrame:
        from ..plans.simrank import multi_source

        return multi_source(None, sources, self.plan, normalization=normalization, tuples=self.tuples())
