"""The corpus pipeline: toxic documents go, one document of each near-duplicate family stays,
documents with benchmark passages go, sources are mixed to their target weights, and the mix is
placed in shards.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; between stages it is written as
Parquet and read again.  All but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from foretell.llm import decontaminate, jaccard_join, mixing, sharding, toxicity
from foretell.llm.common import materialise, table

CATEGORIES = ["low_quality", "toxic"]
N_SHARDS = 8
#: Documents handed to Python at a time, at most: a batch of whole texts is held on both sides of
#: every running task, so its size adds to an executor's memory and changes no result.
BATCH_ROWS = 2000

#: The stages train a model and draw a random mix: not expressible in SQL, so none is given.
ORACLE_SQL = None


def small_batches(spark: SparkSession) -> None:
    """Lower the session's Arrow batches to BATCH_ROWS; smaller ones stay as they are."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxic probability reaches the threshold go."""
    small_batches(spark)
    chain = toxicity.train(docs, toxicity.with_complement(table(spark, sf_dir, "labels")), CATEGORIES)
    return toxicity.without_toxic(docs, chain)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by five-word shingles at similarity 0.8 or more, the least id stays."""
    small_batches(spark)
    return jaccard_join.one_of_each(docs, n=5, num=80, den=100)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which a window of a benchmark item occurs go."""
    small_batches(spark)
    return decontaminate.clean_documents(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mix takes it."""
    small_batches(spark)
    return mixing.mixed_documents(docs)


def place_in_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, size, text_crc32, law, shard and slot of every row of the mix."""
    small_batches(spark)
    placed = sharding.shard_documents(docs, N_SHARDS)
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot")


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("mixing", mix_sources),
    ("sharding", place_in_shards),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
