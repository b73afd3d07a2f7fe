"""Training-data pipeline over the documents table.

Toxic documents go, one document of each near-duplicate group stays, documents that hold a benchmark item go, sources are
mixed to their target weights (documents repeat where the mix takes two copies), and what is left is written as packed token
ids. Each stage works on all rows that the one before it kept, and is written and read again between.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from hypernear.llm import contamination, mixing, order_minhash, packing, toxicity
from hypernear.llm.common import persisted, read, small_batches
from hypernear.sources.storage import fresh_path

TOXIC = 0.7
WIDTH = 2048


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows scored under TOXIC by a model of the labels that are not held out."""
    small_batches(spark)
    scorer = toxicity.fit(docs, read(spark, sf_dir, "labels").filter(~toxicity.held_out()))
    return toxicity.score(docs, scorer, "_toxicity").filter(f"_toxicity < {TOXIC}").drop("_toxicity")


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    small_batches(spark)
    return order_minhash.deduplicated(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    small_batches(spark)
    return contamination.clean(docs, read(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix(docs)


def pack_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packed rows, written as id matrices of WIDTH columns."""
    small_batches(spark)
    return packing.write_matrices(packing.pack_tokens(docs, width=WIDTH), fresh_path(spark, "pipeline-matrices"), width=WIDTH)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_dedup", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("mixing", mix_sources),
    ("packing", pack_ids),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The packed rows of the documents that all stages keep."""
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = persisted(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
