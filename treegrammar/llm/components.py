"""Connected components of a table of links by alternating star contraction, without collecting links to the driver.

``components(spark, links)`` takes links (a, b) of long nodes and returns (node, root), root being the smallest node
that can be reached; only nodes with links to other nodes appear. Tasks first reduce the links they hold to a spanning
forest, then every round points each node to the smallest neighbour (large star), then shortens the chains (small
star). A hub's neighbours are never gathered: only minima are aggregated, with map-side combining, and joined back; those of hubs are broadcast,
at most ``skew.HOT`` of them, so the links of a hub stay where they are.
Every round is written below the shared folder, so that lost executors repeat one round at most.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treegrammar.llm.skew import join_entries
from treegrammar.shared import written


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Star links (node, smallest node of its component) of the graph with these links."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    root = np.arange(len(nodes))
    while True:
        least = np.minimum(root[x], root[y])
        new = root.copy()
        np.minimum.at(new, root[x], least)
        np.minimum.at(new, root[y], least)
        while True:
            jumped = new[new]
            if (jumped == new).all():
                break
            new = jumped
        if (new == root).all():
            break
        root = new
    moved = root != np.arange(len(nodes))
    return nodes[moved], nodes[root[moved]]


def _local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    a, b, held = [], [], 0
    for batch in batches:
        a.append(batch.column(0).to_numpy(zero_copy_only=False))
        b.append(batch.column(1).to_numpy(zero_copy_only=False))
        held += batch.num_rows
        if held > 2_000_000:
            x, y = forest(np.concatenate(a), np.concatenate(b))
            a, b, held = [x], [y], 0
            if len(x) > 1_000_000:
                yield pa.RecordBatch.from_arrays([pa.array(x), pa.array(y)], names=["a", "b"])
                a, b = [], []
    if a:
        x, y = forest(np.concatenate(a), np.concatenate(b))
        yield pa.RecordBatch.from_arrays([pa.array(x), pa.array(y)], names=["a", "b"])


def components(spark: SparkSession, links: DataFrame, max_rounds: int = 60) -> DataFrame:
    own = links.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).where("a <> b")
    now = written(spark, own.mapInArrow(_local, "a long, b long"), "links")
    seen, size = None, now.count()
    for _ in range(max_rounds):
        both = now.union(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n")).select("a", F.least("a", "m").alias("m"), "n")
        least = written(spark, least, "links-least")
        big = join_entries(both.where("b > a"), least, ["a"], "n", 2 * size).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        big = written(spark, big, "links-large-star")
        small = written(spark, big.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n")), "links-least")
        next_ = join_entries(big, small, ["a"], "n", size).select(F.when(F.col("b") == F.col("m"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        now = written(spark, next_, "links")
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        size = mark[0]
        if mark == seen:
            break
        seen = mark
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("root"))
