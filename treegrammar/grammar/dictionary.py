"""A dictionary of frequent patterns, learned on a sample of shards and applied to all of them first.

Its rules name labels and each other, not symbols of one shard, so the same pattern is the same rule everywhere, and
what a query does on it can be worked out once.
"""

from __future__ import annotations

import numpy as np

from treegrammar.grammar.compress import Tree, pairs
from treegrammar.grammar.model import Grammar

Part = tuple[int, str] | int  # a label (kind, name), -1 for null, or the number of an earlier rule from 0


def train(names, events, doc_start, size: int, max_rank: int = 2) -> list[tuple[Part, int, Part]]:
    """The first ``size`` rules that pair replacement makes on a sample."""
    g = pairs(names, events, doc_start, max_rank=max_rank)

    def part(s: int) -> tuple[Part, int] | Part:
        return g.names[s] if s < g.n_labels else (-1 if s == g.null else s - g.first_rule)

    return [(part(int(g.outer[k])), int(g.hole[k]), part(int(g.inner[k]))) for k in range(min(size, g.n_rules))]


def apply(tree: Tree, rules: list[tuple[Part, int, Part]]) -> dict[int, int]:
    """Contract all occurrences of the rules in order; returns the shard's symbol of each rule that its labels allow."""
    label = {n: k for k, n in enumerate(tree.names)}
    symbol: dict[int, int] = {}

    def find(p: Part) -> int | None:
        return label.get(p) if isinstance(p, tuple) else (len(tree.names) if p == -1 else symbol.get(p))

    for k, (outer, hole, inner) in enumerate(rules):
        x, y = find(outer), find(inner)
        if x is None or y is None or tree.rank[x] + tree.rank[y] - 1 > tree.max_rank:
            continue
        at = np.flatnonzero(tree.alive & (tree.parent >= 0) & (tree.sym == y) & (tree.slot == hole - 1))
        at = at[tree.sym[tree.parent[at]] == x]
        if x == y and len(at):
            at = tree.alternate(at)
        symbol[k] = tree.rule(x, hole, y)
        if len(at):
            tree.contract(at, x, hole - 1, y)
    return symbol


def pairs_with(rules: list[tuple[Part, int, Part]]):
    """A compressor that applies the dictionary first and goes on with the shard's own pairs."""

    def compress(names, events, doc_start, open_end: bool = False, max_rank: int = 2) -> Grammar:
        return pairs(names, events, doc_start, open_end, max_rank, before=lambda tree: apply(tree, rules))

    return compress
