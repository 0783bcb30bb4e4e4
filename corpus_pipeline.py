"""The corpus pipeline: toxicity, exact dedup, near dedup, decontamination, and encoding, in this order.

Every stage takes (spark, docs, sf_dir), works on all rows that its predecessor kept, and is written as Parquet below
the shared folder before the next one reads it. All stages but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from treegrammar.llm import bpe, decontaminate, exact_dedup, simhash, toxicity
from treegrammar.llm.queries import table, tokenizer_text
from treegrammar.shared import ship, written


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Stage of operator 8: documents that it rejects go. The model is fitted on labelled rows that are not held out."""
    ship(spark)
    model = toxicity.fit(spark, docs.select("doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return toxicity.clean(spark, docs, model)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Stage of operator 1: of equal texts the longest original with the smallest id stays."""
    ship(spark)
    return exact_dedup.keep_first(spark, docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Stage of operator 3: of each component of linked fingerprints the smallest id stays."""
    ship(spark)
    return simhash.keep_one(spark, docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Stage of operator 5: documents that hold a passage of ``benchmark`` go."""
    ship(spark)
    return decontaminate.clean(spark, docs, table(spark, sf_dir, "benchmark", "item_id", "text"))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Stage of operator 9: the digests of ids and decoded text of every remaining document."""
    ship(spark)
    return bpe.digests(docs.select("doc_id", "text"), tokenizer_text())


STAGES = [("toxicity", drop_toxic), ("exact dedup", drop_copies), ("simhash near-dedup", drop_near_copies), ("decontamination", drop_leaks), ("bpe", tokens)]

#: SQL has no expression for the toxicity votes, the linked fingerprints and the encoder.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = written(spark, stage(spark, docs, sf_dir), "stage-" + name.replace(" ", "-"))
    return docs
