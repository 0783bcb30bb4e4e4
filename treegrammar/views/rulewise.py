"""The rule-wise view: an automaton runs over each rule once in each state.

``Run`` works for one grammar and automaton. The eager form evaluates all rules and states level by level with numpy;
the lazy one follows the start, memoises (rule, state) pairs, jumps over rules without relevant labels, and skips what
lies in the universal state, counting its visits.
"""

from __future__ import annotations

import numpy as np

from treegrammar.grammar.model import Grammar
from treegrammar.xpath.automaton import Automaton


class Counters:
    __slots__ = ("visited", "jumped", "skipped", "memo_hits", "copied")

    def __init__(self) -> None:
        self.visited = self.jumped = self.skipped = self.memo_hits = self.copied = 0


class Run:
    def __init__(self, g: Grammar, a: Automaton, jump: bool = True, fine: bool = True, skip: bool = True):
        self.g, self.a, self.jump, self.skip = g, a, jump, skip
        cls = a.classify(g.names)
        self.label_selects = a.selects[:, cls]  # (states, labels)
        self.label_down, self.label_right = a.to_down[:, cls], a.to_right[:, cls]
        relevant, self.otherwise = a.relevance(fine)
        words = g.masks().shape[1]
        lab = np.arange(g.n_labels)
        self.relevant = np.zeros((a.n_states, words), np.uint64)
        for q in range(a.n_states):
            hot = lab[relevant[q, cls]] if g.n_labels else lab
            np.bitwise_or.at(self.relevant[q], hot >> 6, np.uint64(1) << (hot & 63).astype(np.uint64))
        self.count = Counters()
        self._memo: dict[tuple[int, int], tuple[int, tuple[int, ...]]] = {}

    # Eager

    def tables(self) -> tuple[np.ndarray, np.ndarray]:
        """Selected nodes (symbols, states) and states at the holes (symbols, states, max_rank)."""
        if hasattr(self, "_tables"):
            return self._tables
        g, m, w = self.g, self.a.n_states, self.g.max_rank
        n = g.first_rule + g.n_rules
        cnt, hole = np.zeros((n, m), np.int64), np.zeros((n, m, w), np.int32)
        cnt[: g.n_labels] = self.label_selects.T
        hole[: g.n_labels, :, 0], hole[: g.n_labels, :, 1] = self.label_down.T, self.label_right.T
        from_inner, index = g.splice()
        for rules in g.levels():
            v, x, y, i = g.first_rule + rules, g.outer[rules], g.inner[rules], g.hole[rules] - 1
            hx = hole[x]
            at = np.take_along_axis(hx, np.broadcast_to(i[:, None, None], (len(rules), m, 1)), 2)[..., 0]
            cnt[v] = cnt[x] + cnt[y[:, None], at]
            idx = np.broadcast_to(index[rules][:, None, :], (len(rules), m, w))
            hy = hole[y[:, None], at]
            hole[v] = np.where(from_inner[rules][:, None, :], np.take_along_axis(hy, idx, 2), np.take_along_axis(hx, idx, 2))
        self._tables = (cnt, hole)
        return self._tables

    def eager_count(self, state: int | None = None) -> tuple[np.ndarray, int]:
        """Selected nodes of each document, and the state at the open end (of a run)."""
        cnt, hole = self.tables()
        g = self.g
        q0 = self.a.initial if state is None else state
        start, rank = g.start.tolist(), g.rank.tolist()
        out, exit_ = np.zeros(len(g.doc_start) - 1, np.int64), q0
        bounds = g.doc_start.tolist()
        if len(start) == len(out):  # every document is a single symbol
            out[:] = cnt[g.start, q0]
            return out, q0
        used, at = np.unique(g.start, return_inverse=True)
        at = at.reshape(-1).tolist()
        c, h = cnt[used].tolist(), hole[used].tolist()
        end = g.end
        ranks = [rank[s] for s in used.tolist()]
        is_end = [s == end for s in used.tolist()]
        for d in range(len(out)):
            stack, total = [q0], 0
            for k in at[bounds[d] : bounds[d + 1]]:
                q = stack.pop()
                if is_end[k]:
                    exit_ = q
                    continue
                total += c[k][q]
                r = ranks[k]
                if r:
                    stack += h[k][q][:r][::-1]
            out[d] = total
        return out, exit_

    # Lazy

    def _jumped(self, v: int, q: int) -> tuple[int, tuple[int, ...]] | None:
        if not self.jump or (self.g.masks()[v] & self.relevant[q]).any():
            return None
        r, how = int(self.g.rank[v]), int(self.otherwise[q])
        self.count.jumped += 1
        if how == 0:
            return 0, (q,) * r
        u = self.a.universal
        last = q if how == 2 and self.g.on_spine()[v] else u
        return 0, (u,) * (r - 1) + (last,) if r else ()

    def behaviour(self, v: int, q: int) -> tuple[int, tuple[int, ...]]:
        """Selected nodes of symbol v entered in state q, and the states at its holes."""
        g, memo = self.g, self._memo
        work = [(v, q)]
        while work:
            s, p = work[-1]
            if (s, p) in memo:
                work.pop()
                continue
            if s < g.first_rule:
                self.count.visited += 1
                got = (int(self.label_selects[p, s]), (int(self.label_down[p, s]), int(self.label_right[p, s]))) if s < g.n_labels else (0, ())
            elif self.skip and p == self.a.universal:
                self.count.skipped += 1
                got = (0, (p,) * int(g.rank[s]))
            else:
                got = self._jumped(s, p)
                if got is None:
                    k = s - g.first_rule
                    x, i, y = int(g.outer[k]), int(g.hole[k]) - 1, int(g.inner[k])
                    first = memo.get((x, p))
                    if first is None:
                        work.append((x, p))
                        continue
                    below = first[1][i]
                    second = memo.get((y, below))
                    if second is None:
                        work.append((y, below))
                        continue
                    self.count.visited += 1
                    got = (first[0] + second[0], first[1][:i] + second[1] + first[1][i + 1 :])
            memo[s, p] = got
            work.pop()
        return memo[v, q]

    def lazy_count(self, state: int | None = None) -> tuple[np.ndarray, int]:
        g = self.g
        q0 = self.a.initial if state is None else state
        out, exit_ = np.zeros(len(g.doc_start) - 1, np.int64), q0
        start, ends, bounds = g.start.tolist(), g.start_ends(), g.doc_start.tolist()
        for d in range(len(out)):
            stack, total, k = [q0], 0, bounds[d]
            while k < bounds[d + 1]:
                q, s = stack.pop(), start[k]
                if s == g.end:
                    exit_ = q
                elif self.skip and q == self.a.universal and not (g.open_end and d == len(out) - 1):
                    self.count.skipped += 1
                    k = int(ends[k])
                    continue
                else:
                    if (s, q) in self._memo:
                        self.count.memo_hits += 1
                    n, holes = self.behaviour(s, q)
                    total += n
                    stack += holes[::-1]
                k += 1
            out[d] = total
        return out, exit_
