"""The corpus pipeline: five stages over the documents table, each on all that the one before it kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from simweave.llm.minhash_dedup import keep_one_of_each
from simweave.llm.mixing import repeat_by_mix
from simweave.llm.packing import pack_documents
from simweave.llm.quality import keep_good_documents
from simweave.llm.surrogates import replace_entities
from simweave.plans.shipping import ship
from simweave.plans.staging import keep, scratch, stage


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the document rules and whose host passes; the others go."""
    ship(spark)
    return keep_good_documents(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies."""
    ship(spark)
    return keep_one_of_each(docs)


def pii_surrogates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, personal data replaced; n_chars follows the text."""
    ship(spark)
    replaced = replace_entities(docs, count_col=None)
    return replaced.withColumn("n_chars", F.char_length("text").cast("long"))


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix of sources takes them."""
    ship(spark)
    return repeat_by_mix(docs)


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents, placed in sequences of at most 2048 tokens."""
    ship(spark)
    return pack_documents(docs)


STAGES = [
    ("quality rules", quality_rules),
    ("near-duplicate removal", near_dedup),
    ("surrogates", pii_surrogates),
    ("source mix", source_mix),
    ("packing", best_fit_packing),
]

#: Signatures, keyed surrogates, draws and tokens are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result is a written table, read again by the next stage.

    What a stage has staged for itself is deleted once its result is written.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, apply in STAGES[:-1]:
        with scratch():
            docs = keep(stage(apply(spark, docs, sf_dir), name.replace(" ", "-")))
    return STAGES[-1][1](spark, docs, sf_dir)
