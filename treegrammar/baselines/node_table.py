"""Baseline: a pre/size/level node table and one join for each step.

Child and sibling steps are equi-joins on parents. Descendant steps are range joins: an ancestor's range goes to every bucket
of node numbers that it covers, a node to one bucket, and the range condition is checked within a bucket only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treegrammar.xpath.parse import CHILD, DESCENDANT, Step, parse_path

BUCKET = 256
_KIND = {"element": 0, "text": 1, "attrs": 2, "attr": 4}


def _test(nodes: DataFrame, s: Step) -> DataFrame:
    out = nodes.where(F.col("kind") == _KIND[s.kind])
    return out if s.name is None else out.where(F.col("label") == s.name)


def select(nodes: DataFrame, path: str) -> DataFrame:
    """The rows of a node table (doc_id, node, label, kind, size, parent, ...) that a path selects, each once."""
    here: DataFrame | None = None
    for s in parse_path(path):
        want = _test(nodes, s)
        if here is None:
            here = want.where("parent is null") if s.axis == CHILD else want
        elif s.axis == CHILD:
            up = here.select(F.col("doc_id").alias("d"), F.col("node").alias("p"))
            here = want.join(up, (want["doc_id"] == up["d"]) & (want["parent"] == up["p"]), "left_semi")
        elif s.axis == DESCENDANT:
            first, last = F.floor((F.col("node") + 1) / BUCKET), F.floor((F.col("node") + F.col("size") - 1) / BUCKET)
            up = here.where("size > 1").select(F.col("doc_id").alias("d"), F.col("node").alias("a"), (F.col("node") + F.col("size")).alias("z"), F.explode(F.sequence(first, last)).alias("b"))
            low = want.withColumn("bucket", F.floor(F.col("node") / BUCKET))
            here = low.join(up, (low["doc_id"] == up["d"]) & (low["bucket"] == up["b"]) & (low["node"] > up["a"]) & (low["node"] < up["z"]), "left_semi").drop("bucket")
        else:
            left = here.groupBy(F.col("doc_id").alias("d"), F.col("parent").alias("p")).agg(F.min("node").alias("first"))
            here = want.join(left, (want["doc_id"] == left["d"]) & want["parent"].eqNullSafe(left["p"]) & (want["node"] > left["first"]), "left_semi")
    return here


def count(nodes: DataFrame, path: str) -> DataFrame:
    return select(nodes, path).agg(F.count("*").alias("n"))
