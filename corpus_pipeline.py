"""Corpus pipeline: toxicity filter, exact, near and substring deduplication, packing.

Part of the training-data operators: it goes with the subpackage ``llm``. Each stage
takes (spark, docs, sf_dir); its result is written as Parquet and read again
as the next stage's docs. All but the last return the columns of documents.
"""

from __future__ import annotations

import os
from collections.abc import Callable
from weakref import WeakKeyDictionary

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from echowalk.llm import exact_dedup, packing, simhash, substring_dedup, toxicity
from echowalk.llm.common import discard_paths, numbered, stash, stashed
from echowalk.llm.queries import toxicity_weights

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with scores from 0.3 on go."""
    weights = toxicity_weights(docs, spark, sf_dir)
    return toxicity.add_scores(docs.select(*COLUMNS), weights, score_col="_toxic").filter("_toxic < 0.3").drop("_toxic")


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.keep_one(docs.select(*COLUMNS))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents joined by SimHash fingerprints at 3 or fewer differing bits one stays."""
    return simhash.keep_representatives(docs.select(*COLUMNS))


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts lose repeated windows of 35 words; a text that loses nothing stays as it is."""
    rows = numbered(docs.select(*COLUMNS))
    found = substring_dedup.remove_repeats(rows, window=35, id_col="_row").filter("n_removed > 0").select(F.col("doc_id").alias("_row"), "kept_text")
    joined = rows.join(found, "_row", "left")
    text = F.coalesce("kept_text", "text")
    return joined.withColumns({"text": text, "n_chars": F.when(F.col("kept_text").isNotNull(), F.length("kept_text").cast("long")).otherwise(F.col("n_chars"))}).select(*COLUMNS)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"), capacity=2048, separator=0)


_of_last_stage: WeakKeyDictionary[SparkSession, set[str]] = WeakKeyDictionary()


def _stage(f: Callable[[SparkSession, DataFrame, str], DataFrame]) -> Callable[[SparkSession, DataFrame, str], DataFrame]:
    """Tables that the session's last stage left in the shared folder are deleted when the next one
    begins, but for those that its docs still read: there, the last stage's result is not written yet."""

    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        old = _of_last_stage.get(spark, set())
        read = set(docs.inputFiles()) if old else set()
        kept = {path for path in old if any(os.path.basename(path) in file for file in read)}
        discard_paths(old - kept)
        before = stashed()
        out = f(spark, docs, sf_dir)
        _of_last_stage[spark] = kept | stashed() - before
        return out

    return run


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", _stage(drop_toxic)),
    ("exact_dedup", _stage(drop_exact_copies)),
    ("near_dedup", _stage(drop_near_copies)),
    ("substring_dedup", _stage(drop_repeated_passages)),
    ("packing", _stage(pack_sequences)),
]

#: Learned scores, XXH64 fingerprints and token ids are beyond DuckDB's SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = stash(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
