"""A corpus pipeline of five operators, each working on all that the one before it kept.

Toxic documents go, one document of each near-duplicate class stays, documents that hold a benchmark
item go, the rest is mixed to the sources' target weights (documents come as often as the mix takes
their words), and what the mix holds is dealt to shards. All stages but the last return the columns
of documents; the last adds shard and slot.

Every stage takes nulls in any column, empty and very long texts, ties, repeated rows, empty tables and columns of any name:
documents without a text are clean, near nothing and hold no item, so they pass the first three stages; they hold no word, so the mix
leaves them out. Rows that repeat a text are one class (the least doc_id stays, null last; of its rows the text with the least digest).
An empty table stays empty through all stages. Extra columns are carried along; only `shard` and `slot` are replaced, by the last stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from equidepth.llm import decontaminate, mixing, probminhash, sharding, toxicity
from equidepth.llm.shared import materialize


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that score below the threshold, as they are; a null text scores like an empty one."""
    return toxicity.clean_documents(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each class, that of the least doc_id; rows without a word all stay."""
    return probminhash.keep_one(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that hold no item; null items and items without an id are no items."""
    return decontaminate.without_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows as often as the mix takes their words; null sources are one source, rows without a word do not come back."""
    return mixing.mixed_documents(docs)


def deal_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows with shard and slot; null ids are a key like any other."""
    return sharding.assign_shards(docs, 24)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_copies),
    ("decontamination", drop_leaks),
    ("source_mix", mix_sources),
    ("sharding", deal_shards),
]

#: Models and sketches are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
