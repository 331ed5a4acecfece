"""A training corpus from documents: toxic texts go, near copies go, benchmark passages go, the
rest is mixed to target weights and dealt into shards, whose slots keep the order of the mix. Each stage is written as Parquet and reread.

Every stage takes any table with the columns of documents, nulls, repeated rows and empty tables included, and keeps extra
columns: what a row without text, source or doc_id becomes is said at the operator that the stage calls."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from segforest.llm import decontam, kdshard, mixing, neardup, toxicity
from segforest.llm._common import written


def toxic_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score below 0.5, each row by its text alone; a null text scores as an empty one."""
    return toxicity.without_toxic(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def copies_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest doc_id of each group of near copies, once; texts without words all stay."""
    return neardup.deduplicated(docs, shingle=5, threshold=0.8)


def leaks_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no window of a benchmark item occurs; a text without words stays."""
    return decontam.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, in an order that keeps each source within a block of its weight; mix_position has a row's place."""
    return mixing.in_mixed_order(docs, position=mixing.POSITION)


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents with their columns, size, text_crc32, shard (0 to 39, of near equal bytes) and slot, which follows the mix."""
    return kdshard.sharded(docs, 40, order=mixing.POSITION if mixing.POSITION in docs.columns else None, rest=True)


STAGES = [("toxicity", toxic_out), ("near_duplicates", copies_out), ("decontamination", leaks_out), ("mixing", mix), ("sharding", shard)]

#: The first stage is a fitted model, which SQL does not express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        docs = written(out, f"stage-{name}") if k + 1 < len(STAGES) else out
    return docs
