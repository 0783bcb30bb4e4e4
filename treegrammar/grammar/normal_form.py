"""Grammars with right-hand sides of any size, and their binary normal form.

A right-hand side is a pre-order list of symbols in which ``-1 .. -k`` are the holes in order. Pair replacement makes rules
of two symbols each; ``general`` and ``inline_single`` turn them into fewer, larger rules (a rule that is used once
is put where it is used), and ``normal_form`` goes back: every rule but the start becomes rules of an outer symbol, a hole and an
inner symbol, and equal ones are shared.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from treegrammar.grammar.model import Grammar


@dataclass
class GeneralGrammar:
    names: list[tuple[int, str]]
    rules: dict[int, list[int]]  # number of a symbol -> right-hand side; parts before users
    rank: dict[int, int]
    start: list[int]
    doc_start: list[int]
    open_end: bool

    def edges(self) -> int:
        """Edges of all right-hand sides; holes are edges too."""
        return sum(len(r) - 1 for r in self.rules.values()) + len(self.start) - (len(self.doc_start) - 1)

    def depth(self) -> int:
        deep: dict[int, int] = {}
        for v, rhs in self.rules.items():
            deep[v] = 1 + max((deep.get(s, 0) for s in rhs if s >= 0), default=0)
        return max(deep.values(), default=0)

    def arity(self, s: int) -> int:
        return 0 if s < 0 else self.rank[s]


def general(g: Grammar) -> GeneralGrammar:
    rank = dict(enumerate(g.rank.tolist()))
    rules = {}
    for k, (x, i, y) in enumerate(zip(g.outer.tolist(), g.hole.tolist(), g.inner.tolist(), strict=True)):
        a, b = i - 1, rank[y]
        rules[g.first_rule + k] = [x, *range(-1, -a - 1, -1), y, *range(-a - 1, -a - b - 1, -1), *range(-a - b - 1, -a - b - rank[x], -1)]
    return GeneralGrammar(g.names, rules, rank, g.start.tolist(), g.doc_start.tolist(), g.open_end)


def _children(gg: GeneralGrammar, rhs: list[int]) -> list[list[int]]:
    """For every position the positions of its children."""
    kids: list[list[int]] = [[] for _ in rhs]
    stack: list[int] = []
    for p, s in enumerate(rhs):
        if stack:
            kids[stack[-1]].append(p)
        stack.append(p)
        while stack and len(kids[stack[-1]]) == gg.arity(rhs[stack[-1]]):
            stack.pop()
    return kids


def _inlined(gg: GeneralGrammar, rhs: list[int], chosen: set[int]) -> list[int]:
    """The right-hand side with the chosen rules replaced by theirs, written in one pass from the left."""
    out: list[int] = []
    kids = _children(gg, rhs)
    work: list[tuple[list[int], int, list[list[int]], list | None]] = [(rhs, 0, kids, None)]
    # An entry: a list, a position in it, its children, and what the holes stand for (a list of such entries).
    while work:
        own, p, own_kids, holes = work.pop()
        s = own[p]
        if s < 0:
            if holes is None:
                out.append(s)
            else:
                work.append(holes[-s - 1])
            continue
        args = [(own, c, own_kids, holes) for c in own_kids[p]]
        if s in chosen:
            body = gg.rules[s]
            work.append((body, 0, _children(gg, body), args))
        else:
            out.append(s)
            work += args[::-1]
    return out


def inline_single(gg: GeneralGrammar) -> GeneralGrammar:
    """Rules that are used once are put where they are used; rules that are not used go."""
    uses: dict[int, int] = {}
    for rhs in [*gg.rules.values(), gg.start]:
        for s in rhs:
            if s in gg.rules:
                uses[s] = uses.get(s, 0) + 1
    once = {s for s in gg.rules if uses.get(s, 0) == 1}
    out = GeneralGrammar(gg.names, {}, gg.rank, gg.start, gg.doc_start, gg.open_end)
    flat = GeneralGrammar(gg.names, dict(gg.rules), gg.rank, gg.start, gg.doc_start, gg.open_end)
    for v, rhs in gg.rules.items():
        flat.rules[v] = _inlined(flat, rhs, once & set(rhs))
        if uses.get(v, 0) > 1:
            out.rules[v] = flat.rules[v]
    starts: list[int] = []
    bounds = [0]
    for b, e in zip(gg.doc_start[:-1], gg.doc_start[1:], strict=True):
        own = gg.start[b:e]
        starts += _inlined(flat, own, once & set(own))
        bounds.append(len(starts))
    out.start, out.doc_start = starts, bounds
    return out


def normal_form(gg: GeneralGrammar) -> Grammar:
    """Binary normal form of every rule but the start."""
    base = len(gg.names) + 2
    rank = [2] * len(gg.names) + [0, 0]
    triples: list[tuple[int, int, int]] = []
    made: dict[tuple[int, int, int], int] = {}
    symbol = {s: s for s in range(base)}

    def rule(x: int, i: int, y: int) -> int:
        key = (x, i, y)
        if key not in made:
            made[key] = len(rank)
            rank.append(rank[x] + rank[y] - 1)
            triples.append(key)
        return made[key]

    for v, rhs in gg.rules.items():
        kids = _children(gg, rhs)
        folded: dict[int, int] = {}
        for p in range(len(rhs) - 1, -1, -1):
            if rhs[p] < 0:
                continue
            z = symbol[rhs[p]]
            for k in range(len(kids[p]), 0, -1):
                if kids[p][k - 1] in folded:
                    z = rule(z, k, folded[kids[p][k - 1]])
            folded[p] = z
        symbol[v] = folded[0]
    t = np.array(triples, np.int64).reshape(-1, 3)
    return Grammar(gg.names, t[:, 0], t[:, 1], t[:, 2], np.array(rank, np.int64), np.array([symbol[s] for s in gg.start], np.int64), np.array(gg.doc_start, np.int64), gg.open_end)


def shapes(g: Grammar) -> dict[str, float]:
    """Start, rules, edges and depth before and after the normal form, and the growth of the size in percent."""
    before = inline_single(general(g))
    after = normal_form(before)
    a, b = before.edges(), after.edges()
    return {
        "start": len(before.start), "rules_before": len(before.rules), "rules_after": after.n_rules, "depth_before": before.depth(), "depth_after": after.depth(),
        "edges_before": a, "edges_after": b, "growth_percent": 100.0 * (b - a) / max(1, a), "rank_before": max((before.rank[v] for v in before.rules), default=0), "rank_after": int(after.rank[after.first_rule :].max(initial=0)),
    }
