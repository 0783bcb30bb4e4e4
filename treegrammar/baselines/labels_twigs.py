"""Baselines over per-label node lists: label positions of a succinct index, and two twig joins."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treegrammar.baselines.path_index import path_regex
from treegrammar.xpath.parse import CHILD, parse_path


def label_positions(nodes: DataFrame) -> DataFrame:
    """(section, shard_no, doc_id, label, positions): the sorted node numbers of each label, shard by shard."""
    return nodes.where("kind = 0").groupBy("section", "shard_no", "doc_id", "label").agg(F.array_sort(F.collect_list("node")).alias("positions"))


def label_count(positions: DataFrame, label: str, within: tuple[int, int] | None = None) -> DataFrame:
    """How often a label occurs, or how often from node ``within[0]`` on and before ``within[1]`` (a subtree)."""
    own = F.col("positions") if within is None else F.filter("positions", lambda p: (p >= within[0]) & (p < within[1]))
    return positions.where(F.col("label") == label).agg(F.coalesce(F.sum(F.size(own)), F.lit(0)).cast("long").alias("n"))


def topmost_sum(nodes: DataFrame, above: str, below: str) -> DataFrame:
    """The count of //above//below as a sum of subtree counts over the topmost ``above`` nodes, each by two binary searches."""

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        table = table.sort_by("node")
        label = np.array(table.column("label").to_pylist(), object)
        node, size = table.column("node").to_numpy(), table.column("size").to_numpy()
        a, b = np.flatnonzero(label == above), node[label == below]
        total, end = 0, -1
        for k in a.tolist():
            if node[k] >= end:
                end = int(node[k] + size[k])
                total += int(np.searchsorted(b, end) - np.searchsorted(b, node[k] + 1))
        return pa.table({"n": pa.array([total], pa.int64())})

    cut = nodes.where((F.col("kind") == 0) & F.col("label").isin(above, below)).select("section", "shard_no", "doc_id", "node", "label", "size")
    return cut.groupBy("section", "shard_no", "doc_id").applyInArrow(run, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def twig_stack(nodes: DataFrame, path: str) -> DataFrame:
    """(doc_id, node): the streams of the query's labels merged in document order with a stack of ancestors.

    An ancestor on the stack knows which prefixes of the path end at it or above it; the shards of a giant document start
    with the elements above their records, read off the first record's label path."""
    steps = parse_path(path)
    names = {s.name for s in steps}
    # A child step needs its parent even if that has another label: then all elements are in the stream.
    direct = any(s.axis == CHILD for s in steps)
    stream = nodes.where("kind = 0")
    if not direct and None not in names:
        stream = stream.where(F.col("label").isin(sorted(names)))
    ends = len(steps)

    def advance(label: str, direct_bits: int, above_bits: int) -> int:
        out = 0
        for i, s in enumerate(steps):
            if s.name in (None, label) and (direct_bits if s.axis == CHILD else above_bits) >> i & 1:
                out |= 1 << (i + 1)
        return out

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        table = table.sort_by("node")
        rows = list(zip(table.column("node").to_pylist(), table.column("size").to_pylist(), table.column("label").to_pylist(), strict=True))
        bits, above = 1, 1  # bit i: the first i steps are matched by the parent; by it or an ancestor
        if key[0].as_py() >= 0 and rows:
            first = table.column("path")[0].as_py().split("/")[1:]
            depth = table.column("level")[0].as_py()
            tops = first[:depth] if table.column("shard_no")[0].as_py() is not None else []
            root = table.column("parent")[0].as_py() is None
            for name in [] if root else tops:
                bits = advance(name, bits, above)
                above |= bits
        stack: list[tuple[int, int, int]] = []
        out = []
        for node, size, label in rows:
            while stack and stack[-1][0] <= node:
                stack.pop()
            d, a = (stack[-1][1], stack[-1][2]) if stack else (bits, above)
            own = advance(label, d, a)
            if own >> ends & 1:
                out.append(node)
            stack.append((node + size, own, a | own))
        doc = table.column("doc_id")[0].as_py() if rows else 0
        return pa.table({"doc_id": pa.array([doc] * len(out), pa.int64()), "node": pa.array(out, pa.int64())})

    cut = stream.select("section", "shard_no", "doc_id", "node", "size", "label", "level", "parent", "path")
    return cut.groupBy("section", "shard_no", "doc_id").applyInArrow(run, "doc_id long, node long")


def twig_leaf(nodes: DataFrame, path: str) -> DataFrame:
    """(doc_id, node): the stream of the last step's label, each checked against the labels above it."""
    last = parse_path(path)[-1]
    leaf = nodes.where((F.col("kind") == {"element": 0, "text": 1, "attrs": 2, "attr": 4}[last.kind]) & (F.lit(True) if last.name is None else F.col("label") == last.name))
    return leaf.where(F.col("path").rlike(path_regex(path))).select("doc_id", "node")
