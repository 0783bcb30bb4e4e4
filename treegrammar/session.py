"""The front door: carriers, builds, loads and the SQL surface of one Spark session."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treegrammar.functions import tree_functions
from treegrammar.operators.index import SHARD_NODES, TreeIndex
from treegrammar.shared import ship
from treegrammar.sources.carriers import Carrier, carrier


class TreeGrammar:
    def __init__(self, spark: SparkSession):
        self.spark = spark
        ship(spark)

    def carrier(self, name: str, sf_dir: str) -> Carrier:
        return carrier(self.spark, name, sf_dir)

    def documents(self, docs: DataFrame, doc_id: str, content: str, name: str = "documents", policy: str = "strict") -> Carrier:
        """Any table of markup as a carrier; policy ``html`` reads web pages tolerantly."""
        rows = docs.select(F.lit(name).alias("carrier"), F.lit(0).alias("section"), F.col(doc_id).cast("long").alias("ord"), F.col(doc_id).cast("long").alias("doc_id"), F.col(content).alias("content"))
        return Carrier(name, rows, None, policy)

    def build(self, source: Carrier, path: str | None = None, compressor: str = "pairs", max_rank: int = 2, shard_nodes: int = SHARD_NODES, dictionary: int = 0) -> TreeIndex:
        return TreeIndex.build(self.spark, source, path, compressor, max_rank, shard_nodes, dictionary)

    def load(self, path: str) -> TreeIndex:
        return TreeIndex.load(self.spark, path)

    def sql_functions(self) -> None:
        """shred, xpath_results, xpath_count_html and markup_tokens for SQL."""
        tree_functions.register(self.spark)

    def tree(self, index: TreeIndex, path: str, view: str) -> DataFrame:
        """The results of a path as a temporary view (doc_id, pre, piece_no, xml)."""
        df = index.serialize(path)
        df.createOrReplaceTempView(view)
        return df
