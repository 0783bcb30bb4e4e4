"""Straight-line tree grammars in binary normal form, as arrays.

Symbols: labels ``0 .. L-1`` of rank 2 (first child, next sibling), the null leaf ``L``, the open end of a sibling run
``L+1`` (rank 0, never shared), then rules. A rule (outer X, hole i from 1, inner Y) stands for X with Y put at its i-th
hole. Rules come after their parts. The start is the list of remaining symbols of all documents in pre-order.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

MAX_SYMBOL, MAX_RULE_RANK = 1 << 28, 15


class GrammarLimitError(ValueError):
    """A rule does not fit into the packed form."""


@dataclass
class Grammar:
    names: list[tuple[int, str]]
    outer: np.ndarray
    hole: np.ndarray
    inner: np.ndarray
    rank: np.ndarray  # of every symbol
    start: np.ndarray
    doc_start: np.ndarray  # one more than documents
    open_end: bool = False
    tables: dict = field(default_factory=dict, repr=False)

    @property
    def n_labels(self) -> int:
        return len(self.names)

    @property
    def null(self) -> int:
        return len(self.names)

    @property
    def end(self) -> int:
        return len(self.names) + 1

    @property
    def first_rule(self) -> int:
        return len(self.names) + 2

    @property
    def n_rules(self) -> int:
        return len(self.outer)

    @property
    def max_rank(self) -> int:
        return max(2, int(self.rank.max(initial=2)))

    def levels(self) -> list[np.ndarray]:
        """Numbers of the rules by level: one more than the higher of the two parts."""
        if "levels" not in self.tables:
            f, lvl = self.first_rule, np.zeros(self.first_rule + self.n_rules, np.int64)
            for k, (x, y) in enumerate(zip(self.outer.tolist(), self.inner.tolist(), strict=True)):
                lvl[f + k] = 1 + max(lvl[x], lvl[y])
            own = lvl[f:]
            order = np.argsort(own, kind="stable")
            cuts = np.flatnonzero(np.diff(own[order])) + 1
            self.tables["levels"] = [x for x in np.split(order, cuts) if len(x)]
        return self.tables["levels"]

    def depth(self) -> int:
        return len(self.levels())

    def splice(self) -> tuple[np.ndarray, np.ndarray]:
        """Where each hole of a rule comes from: (rules, max_rank) of 0 outer or 1 inner, and the hole there."""
        if "splice" not in self.tables:
            k = np.arange(self.max_rank)[None, :]
            i, ry = self.hole[:, None] - 1, self.rank[self.inner][:, None]
            of_inner = (k >= i) & (k < i + ry)
            index = np.where(k < i, k, np.where(of_inner, k - i, k - ry + 1))
            self.tables["splice"] = (of_inner, np.clip(index, 0, self.max_rank - 1))
        return self.tables["splice"]

    def chunks(self, kind: str) -> np.ndarray:
        """Counts of elements, texts or nodes in the rank + 1 stretches between the holes of every symbol."""
        key = "chunks_" + kind
        if key not in self.tables:
            n, w = self.first_rule + self.n_rules, self.max_rank + 1
            out = np.zeros((n, w), np.int64)
            take = {"elem": (0,), "text": (1, 3), "node": (0, 1, 2, 3, 4)}[kind]
            out[: self.n_labels, 0] = [k in take for k, _ in self.names]
            f = self.first_rule
            for rules in self.levels():
                x, y, i = self.outer[rules], self.inner[rules], self.hole[rules]
                ry = self.rank[y]
                c = np.arange(w)[None, :]
                i0 = (i - 1)[:, None]
                r = ry[:, None]
                a, b = out[x], out[y]
                from_x = np.where(c <= i0, c, np.where(c >= i0 + r, c - r + 1, -1))
                got = np.where(from_x >= 0, np.take_along_axis(a, np.clip(from_x, 0, w - 1), 1), 0)
                # With a rank-0 inner symbol three stretches meet in one: before the hole, the inner one, after it.
                none = (r == 0) & (c == i0)
                got = np.where(none, np.take_along_axis(a, np.clip(i0, 0, w - 1), 1) + np.take_along_axis(a, np.clip(i0 + 1, 0, w - 1), 1), got)
                from_y = np.where((c >= i0) & (c <= i0 + r), c - i0, -1)
                got = got + np.where(from_y >= 0, np.take_along_axis(b, np.clip(from_y, 0, w - 1), 1), 0)
                got[c > (self.rank[f + rules])[:, None]] = 0
                out[f + rules] = got
            self.tables[key] = out
        return self.tables[key]

    def masks(self) -> np.ndarray:
        """The jump table: for every symbol, 64-bit words with a bit for each label that it generates."""
        if "masks" not in self.tables:
            words = max(1, -(-self.n_labels // 64))
            out = np.zeros((self.first_rule + self.n_rules, words), np.uint64)
            lab = np.arange(self.n_labels)
            out[lab, lab >> 6] = np.uint64(1) << (lab & 63).astype(np.uint64)
            for rules in self.levels():
                out[self.first_rule + rules] = out[self.outer[rules]] | out[self.inner[rules]]
            self.tables["masks"] = out
        return self.tables["masks"]

    def on_spine(self) -> np.ndarray:
        """Whether the last hole of each symbol lies on the path of second children from its root."""
        if "spine" not in self.tables:
            out = np.zeros(self.first_rule + self.n_rules, bool)
            out[: self.n_labels] = True
            for rules in self.levels():
                x, y, i = self.outer[rules], self.inner[rules], self.hole[rules]
                last = i == self.rank[x]
                out[self.first_rule + rules] = np.where(last, out[x] & out[y] & (self.rank[y] > 0), out[x])
            self.tables["spine"] = out
        return self.tables["spine"]

    def start_ends(self) -> np.ndarray:
        """For every start position the position after its subtree (the explicit shape table)."""
        if "ends" not in self.tables:
            arity = self.rank[self.start].tolist()
            ends = [0] * len(arity)
            stack: list[list[int]] = []
            for k, a in enumerate(arity):
                stack.append([k, a])
                while stack and stack[-1][1] == 0:
                    ends[stack.pop()[0]] = k + 1
                    if stack:
                        stack[-1][1] -= 1
            self.tables["ends"] = np.array(ends, np.int64)
        return self.tables["ends"]

    def start_skips(self, kind: str) -> np.ndarray:
        """Elements or texts generated by the subtree at every start position."""
        total = np.concatenate([[0], np.cumsum(self.chunks(kind)[self.start].sum(axis=1))])
        return total[self.start_ends()] - total[:-1]

    def edges(self) -> int:
        """Edges of all right-hand sides; documents count as trees of their own."""
        return int((self.rank[self.first_rule :] + 1).sum()) + max(0, len(self.start) - (len(self.doc_start) - 1))

    def totals(self, kind: str) -> np.ndarray:
        """Elements, texts or nodes of each document."""
        per = np.concatenate([[0], np.cumsum(self.chunks(kind)[self.start].sum(axis=1))])
        return per[self.doc_start[1:]] - per[self.doc_start[:-1]]

    def expand(self) -> np.ndarray:
        """The parenthesis stream of the start: labels where nodes open, -1 where they close, -2 at an open end."""
        memo: dict[int, list[np.ndarray]] = {}
        none = np.empty(0, np.int32)
        for lab in range(self.n_labels):
            memo[lab] = [np.array([lab], np.int32), none, none]
        memo[self.null], memo[self.end] = [np.array([-1], np.int32)], [np.array([-2], np.int32)]
        used = set(self.start.tolist())
        need = sorted(self._closure(used))
        for v in need:
            x, i, y = int(self.outer[v - self.first_rule]), int(self.hole[v - self.first_rule]), int(self.inner[v - self.first_rule])
            memo[v] = splice_chunks(memo[x], i, memo[y], lambda parts: np.concatenate(parts))
        out: list[np.ndarray] = []
        pending: list[tuple[list[np.ndarray], int]] = []
        for s in self.start.tolist():
            parts = memo[s]
            out.append(parts[0])
            pending.append((parts, 1))
            while pending:
                parts, k = pending.pop()
                if k == len(parts):  # complete
                    if pending:
                        up, j = pending.pop()
                        out.append(up[j])
                        pending.append((up, j + 1))
                    continue
                pending.append((parts, k))
                break
        return np.concatenate(out) if out else none

    def _closure(self, used: set[int]) -> set[int]:
        out: set[int] = set()
        work = [s for s in used if s >= self.first_rule]
        while work:
            v = work.pop()
            if v not in out:
                out.add(v)
                k = v - self.first_rule
                work += [s for s in (int(self.outer[k]), int(self.inner[k])) if s >= self.first_rule and s not in out]
        return out


def splice_chunks(x: list, i: int, y: list, join) -> list:
    """The stretches of outer x with inner y at hole i (from 1); join puts stretches of one side by side."""
    if len(y) == 1:
        return [*x[: i - 1], join([x[i - 1], y[0], x[i]]), *x[i + 1 :]]
    return [*x[: i - 1], join([x[i - 1], y[0]]), *y[1:-1], join([y[-1], x[i]]), *x[i + 1 :]]


def pack(grammar: Grammar) -> np.ndarray:
    """Each rule as one 64-bit word: 28 bits for either symbol, 4 for the hole, 4 for the rank."""
    rank = grammar.rank[grammar.first_rule :]
    if len(rank) and (rank.max() > MAX_RULE_RANK or grammar.hole.max() > MAX_RULE_RANK):
        raise GrammarLimitError(f"rank {int(rank.max())} is above {MAX_RULE_RANK}")
    if len(rank) and max(grammar.outer.max(), grammar.inner.max()) >= MAX_SYMBOL:
        raise GrammarLimitError("a symbol needs more than 28 bits")
    u = np.uint64
    word = grammar.outer.astype(u) << u(36) | grammar.inner.astype(u) << u(8) | grammar.hole.astype(u) << u(4) | rank.astype(u)
    return word.view(np.int64)


def unpack(words: np.ndarray, n_labels: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Outer, hole, inner of the rules and the ranks of all symbols."""
    w = np.asarray(words, np.int64).view(np.uint64)
    u = np.uint64
    outer, inner = (w >> u(36)).astype(np.int64), (w >> u(8) & u(MAX_SYMBOL - 1)).astype(np.int64)
    hole, rank = (w >> u(4) & u(15)).astype(np.int64), (w & u(15)).astype(np.int64)
    return outer, hole, inner, np.concatenate([np.full(n_labels, 2), [0, 0], rank]).astype(np.int64)


def ranked_tree(events: np.ndarray, doc_start: np.ndarray, n_labels: int, open_end: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Symbol, parent and slot of every node of the first-child/next-sibling trees, nulls included, in pre-order.

    In the parenthesis stream, an opening is a node and a closing is the null that ends a list of children, so the
    binary pre-order is the stream itself, followed by the null that ends the list of roots (the open end in a run).
    """
    docs = len(doc_start) - 1
    n = len(events) + docs
    ends = np.asarray(doc_start[1:], np.int64) + np.arange(docs)  # where the nulls of the lists of roots stand
    own = np.ones(n, bool)
    own[ends] = False
    place = np.flatnonzero(own)
    sym, parent, slot = np.full(n, n_labels, np.int64), np.full(n, -1, np.int64), np.zeros(n, np.int64)
    is_open = np.asarray(events) >= 0
    sym[place[is_open]] = np.asarray(events)[is_open]
    if open_end and docs:
        sym[ends[-1]] = n_labels + 1
    # An opening is followed by its first child or null; a closing by the next sibling or null of the node that it closes.
    depth = np.cumsum(np.where(is_open, 1, -1)) + ~is_open
    order = np.argsort(depth.astype(np.int16) if depth.max(initial=0) < 1 << 15 else depth, kind="stable")  # opening, closing, opening, closing
    above = np.empty(n, np.int64)
    above[place[is_open]] = place[is_open]
    above[place[order[1::2]]] = place[order[::2]]
    after = place + 1
    parent[after] = above[place]
    slot[after] = ~is_open
    return sym, parent, slot
