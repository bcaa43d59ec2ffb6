"""Reading and writing tables, edge lists, scores and walk indexes."""

from __future__ import annotations

import atexit
import contextlib
import re
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
_written: list[tuple[SparkSession, str]] = []


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_tables(spark: SparkSession, sf_dir: str, names=TABLES) -> dict[str, DataFrame]:
    return {n: read(spark, sf_dir, n) for n in names}


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share; a local one only where the session names none and
    all runs on one machine."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base and not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
    return base or f"/tmp/checkpoints/{spark.sparkContext.applicationId}"


def keep(df: DataFrame, label: str = "step") -> DataFrame:
    """Write to the folder that driver and executors share, and read back: cuts lineage and outlives
    lost executors."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _written.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


@atexit.register
def _clear() -> None:
    for spark, path in _written:
        with contextlib.suppress(Exception):  # the session may have ended
            at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def require(df: DataFrame, **columns: str) -> DataFrame:
    """``df`` narrowed to the given columns, cast to their types; raises if one is missing."""
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns {missing}; there are {df.columns}")
    return df.select(*(F.col(c).cast(t).alias(c) for c, t in columns.items()))


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", src: str = "src", dst: str = "dst", sep: str = "\t", comment: str = "#") -> DataFrame:
    """(src, dst) from an edge list: csv (two columns, comment lines skipped), json or parquet."""
    schema = T.StructType([T.StructField(src, T.LongType()), T.StructField(dst, T.LongType())])
    if fmt == "csv":
        df = spark.read.csv(path, sep=sep, comment=comment, schema=schema)
    elif fmt == "json":
        df = spark.read.json(path, schema=schema)
    elif fmt == "parquet":
        df = spark.read.parquet(path)
    else:
        raise ValueError(fmt)
    return df.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"))


def write_scores(df: DataFrame, path: str, mode: str = "errorifexists") -> None:
    df.select("source", "node", "score").write.mode(mode).parquet(path)


def write_index(tuples: DataFrame, path: str, buckets: int = 64, mode: str = "errorifexists") -> None:
    """Walk tuples by step, and within a step by (pair, node)."""
    tuples.repartition(buckets, "step", "pair", "node").sortWithinPartitions("step", "pair", "node").write.mode(mode).partitionBy("step").parquet(path)
