"""Baselines over root-to-node label paths: a sorted reversed-path index for simple paths, and path summaries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treegrammar.xpath.parse import CHILD, DESCENDANT, UnsupportedPathError, parse_path


def reversed_path(path: Column) -> Column:
    """Labels from the node up to the root, each followed by a slash."""
    return F.concat(F.array_join(F.reverse(F.split(F.substring(path, 2, 1 << 30), "/")), "/"), F.lit("/"))


def build(nodes: DataFrame, per_node: bool = False) -> DataFrame:
    """The speed form has a row for each node, in the order of reversed paths; the small form one for each distinct path with its count."""
    rows = nodes.select(reversed_path(F.col("path")).alias("rev"), "doc_id", "node")
    if per_node:
        return rows.sortWithinPartitions("rev")
    return rows.groupBy("rev").agg(F.count("*").alias("n"))


def key_of(path: str) -> tuple[str, bool]:
    """The reversed prefix of a simple path, and whether the path starts at the root."""
    steps = parse_path(path)
    if any(s.axis != CHILD for s in steps[1:]) or any(s.name is None and s.kind not in ("text", "attrs") for s in steps):
        raise UnsupportedPathError("the path index answers //a1/../an and /a1/../an only")
    names = ["_T" if s.kind == "text" else "_A" if s.kind == "attrs" else s.name for s in steps]
    return "".join(n + "/" for n in reversed(names)), steps[0].axis == CHILD


def count(index: DataFrame, path: str) -> DataFrame:
    """A range of the sorted paths: a prefix search, pushed down to the scan of a stored index."""
    key, rooted = key_of(path)
    hit = index.where(F.col("rev") == key) if rooted else index.where(F.col("rev").startswith(key))
    n = F.sum("n") if "n" in index.columns else F.count("*")
    return hit.agg(F.coalesce(n, F.lit(0)).cast("long").alias("n"))


def summary(nodes: DataFrame, k: int | None = None, per_label: dict[str, int] | None = None) -> DataFrame:
    """(path, n): with k the last k labels only (an A(k) index), with per_label a k for each last label (a D(k) index),
    with neither all distinct paths (a DataGuide, and on trees the 1-index)."""
    path = F.col("path")
    if k is not None or per_label:
        labels = F.split(F.substring(path, 2, 1 << 30), "/")
        last = F.lit(k or 1)
        for name, own in (per_label or {}).items():
            last = F.when(F.col("label") == name, F.lit(own)).otherwise(last)
        cut = F.least(F.size(labels), last)
        path = F.when(F.size(labels) <= last, path).otherwise(F.array_join(F.slice(labels, F.size(labels) - cut + 1, cut), "/"))
    return nodes.select(path.alias("path")).groupBy("path").agg(F.count("*").alias("n"))


def path_regex(path: str) -> str:
    """A pattern for label paths that a path of child and descendant steps selects."""
    out = "^"
    for s in parse_path(path):
        if s.axis not in (CHILD, DESCENDANT):
            raise UnsupportedPathError("label paths know no siblings")
        name = {"text": "_T", "attrs": "_A"}.get(s.kind) or (s.name and s.name.replace(".", r"\.").replace("-", r"\-"))
        if name is None:
            name = r"@[^/]+" if s.kind == "attr" else r"[^/_@][^/]*|_(?!T(?:/|$)|A(?:/|$)|AT(?:/|$))[^/]*"
        out += ("(?:/[^/]+)*" if s.axis == DESCENDANT else "") + f"/(?:{name})"
    return out + "$"


def estimate(index: DataFrame, path: str, k: int) -> DataFrame:
    """Upper bound of a count from an A(k) index: entries whose last labels fit the last steps; exact if the path is no longer than k."""
    steps = parse_path(path)
    tail = steps[-k:]
    text = "".join(("//" if i == 0 or s.axis == DESCENDANT else "/") + (s.name or ("text()" if s.kind == "text" else "*")) for i, s in enumerate(tail))
    pattern = path_regex(text)[1:].replace("(?:/[^/]+)*/", "^(?:.*/)?", 1)
    return index.where(F.col("path").rlike(pattern)).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))
