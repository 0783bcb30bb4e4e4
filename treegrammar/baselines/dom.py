"""Baseline: a tree-at-a-time interpreter, Spark's own XPath functions on the text of each document."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def count(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, n) over documents (doc_id, xml); the path is parsed and run for every row."""
    return docs.select("doc_id", F.xpath_long("xml", F.lit(f"count({path})")).alias("n"))


def values(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, value) of a path that ends in text() or an attribute."""
    return docs.select("doc_id", F.explode(F.xpath("xml", F.lit(path))).alias("value"))
