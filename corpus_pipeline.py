"""The corpus pipeline: five stages over the documents table, each written as Parquet and read again as the next one's docs.

Null texts count as empty: they aren't toxic, fail the quality rules and go there. Rows with a null id are judged by all
stages but near duplicates, in which they take no part. Repeated rows are exact copies, so one of them stays; rows that share
an id only are judged each by its own text.
An empty table gives an empty result. Columns beside those of documents are dropped at the start.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from levelwave.llm import exact, minhash, packing, quality, toxicity
from levelwave.llm.shared import DOCUMENT_COLUMNS, documents, removed, settled


def without_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score is below the threshold."""
    return toxicity.drop_toxic(docs.select(DOCUMENT_COLUMNS), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def of_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and aren't outliers of their language and source."""
    return quality.drop_rejected(docs)


def without_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the document with the smallest id."""
    return exact.drop_copies(docs)


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates the document with the smallest id."""
    return minhash.drop_near_copies(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of training sequences that hold all that is left."""
    import public_tokenizers

    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("toxicity", without_toxic),
    ("quality", of_quality),
    ("exact dedup", without_copies),
    ("near dedup", without_near_copies),
    ("packing", packed),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages, one after another; what each keeps is in shared scratch space before the next one reads it, and is removed
    when that one is done."""
    docs, before = documents(spark, sf_dir), None
    for name, stage in STAGES:
        docs, path = settled(spark, lambda stage=stage, docs=docs: stage(spark, docs, sf_dir), name.replace(" ", "-"))
        if before:
            removed(spark, before)
        before = path
    return docs


#: No stage but exact dedup can be written in SQL, so the pipeline is tested against brute force instead.
ORACLE_SQL = None
