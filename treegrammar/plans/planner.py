"""Rewrites above Catalyst: how a count is answered, and what the shards are asked.

Catalyst optimises the DataFrames that come out; what it cannot know (label totals, simple-path dictionaries, a root
label that stands at the root only) is decided here. ``explain`` shows both levels.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treegrammar.baselines import path_index
from treegrammar.operators.index import TreeIndex
from treegrammar.xpath.automaton import compile_path
from treegrammar.xpath.parse import CHILD, DESCENDANT, UnsupportedPathError, parse_path


@dataclass
class CountPlan:
    path: str
    method: str  # label_total, simple_path, topmost_sum, rule_wise
    asked: str
    reason: str


def anchor_root(index: TreeIndex, path: str) -> str:
    """A leading //root becomes /root where that label stands only at the root: the automaton then dies early elsewhere."""
    steps = parse_path(path)
    if index.spine is None or steps[0].axis != DESCENDANT or steps[0].name != index.spine.name:
        return path
    inside = index.shards.where(F.array_contains("labels", index.spine.name)).limit(1).count()
    return path[1:] if not inside else path


def plan_count(index: TreeIndex, path: str, paths: DataFrame | None = None, totals: DataFrame | None = None) -> CountPlan:
    """Choose how to count: a stored label total, the simple-path dictionary, or the rule-wise run."""
    asked = anchor_root(index, path)
    steps = parse_path(asked)
    if totals is not None and len(steps) == 1 and steps[0].axis == DESCENDANT and steps[0].kind == "element" and steps[0].name:
        return CountPlan(path, "label_total", asked, "a label query over stored totals")
    if paths is not None:
        try:
            path_index.key_of(asked)
            return CountPlan(path, "simple_path", asked, "a simple path over the distinct-path dictionary")
        except UnsupportedPathError:
            pass
    return CountPlan(path, "rule_wise", asked, f"an automaton of {compile_path(asked).n_states} states over the rules")


def run_count(index: TreeIndex, plan: CountPlan, paths: DataFrame | None = None, totals: DataFrame | None = None) -> DataFrame:
    if plan.method == "label_total":
        return totals.where(F.col("label") == parse_path(plan.asked)[0].name).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))
    if plan.method == "simple_path":
        return path_index.count(paths, plan.asked)
    return index.count(plan.asked)


def label_totals(index: TreeIndex) -> DataFrame:
    """(label, n) of all elements, from the path dictionary of the decompressed nodes."""
    return index.nodes().where("kind = 0").groupBy("label").agg(F.count("*").alias("n"))


def explain(index: TreeIndex, plan: CountPlan) -> str:
    """The chosen plan and the physical plan of the DataFrame behind it."""
    df = index.count(plan.asked)
    text = df._jdf.queryExecution().toString()
    return f"{plan.method}: {plan.asked} ({plan.reason})\n" + re.sub(r"\n+", "\n", text)


__all__ = ["CHILD", "CountPlan", "anchor_root", "explain", "label_totals", "plan_count", "run_count"]
