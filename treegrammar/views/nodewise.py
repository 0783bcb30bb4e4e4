"""The node-wise view: a cursor over the binary tree of a grammar.

A node is a chain of steps from a start position into the outer or inner part of rules, down to a label. Chains are
interned, so nodes share prefixes; ``pool=False`` copies them instead, for comparison. No move uses recursion.
"""

from __future__ import annotations

import zlib

from treegrammar.grammar.model import Grammar

OUTER, INNER = 0, 1


class Cursor:
    def __init__(self, g: Grammar, pool: bool = True):
        self.g, self.pool = g, pool
        self.x, self.i, self.y, self.rank = g.outer.tolist(), g.hole.tolist(), g.inner.tolist(), g.rank.tolist()
        self.start, self.ends, self.f = g.start.tolist(), g.start_ends().tolist(), g.first_rule
        self.up: list[tuple[int, int]] = [(-1, 0)] * len(self.start)
        stack: list[list[int]] = []
        for k, s in enumerate(self.start):
            if stack:
                stack[-1][1] += 1
                self.up[k] = (stack[-1][0], stack[-1][1])
            stack.append([k, 0])
            while stack and stack[-1][1] == self.rank[self.start[stack[-1][0]]]:
                stack.pop()
        self._ids: dict[tuple[int, int, int], int] = {}
        self._of: list[tuple[int, int, int]] = []

    # Chains: None-terminated links (previous, rule, side); a start position p is the chain (-1 - p).

    def _down(self, chain, rule: int, side: int):
        if not self.pool:
            return (*chain, (rule, side)) if isinstance(chain, tuple) else (chain, (rule, side))
        key = (chain, rule, side)
        got = self._ids.get(key)
        if got is None:
            got = self._ids[key] = len(self._of)
            self._of.append(key)
        return got

    def _last(self, chain):
        """(previous chain, rule, side), or None at a start position."""
        if not self.pool:
            if not isinstance(chain, tuple):
                return None
            prev = chain[:-1] if len(chain) > 2 else chain[0]
            return prev, *chain[-1]
        return self._of[chain] if chain >= 0 else None

    def symbol(self, chain) -> int:
        last = self._last(chain)
        if last is None:
            return self.start[-1 - chain]
        _, v, side = last
        return (self.y if side else self.x)[v - self.f]

    def _root(self, chain):
        """The chain of the label at the root of the symbol that the chain leads to."""
        s = self.symbol(chain)
        while s >= self.f:
            chain = self._down(chain, s, OUTER)
            s = self.x[s - self.f]
        return chain

    def at_hole(self, chain, k: int):
        """The chain of the symbol that stands at hole k (from 1) of the symbol at the end of ``chain``."""
        while True:
            last = self._last(chain)
            if last is None:
                p = -1 - chain
                q = p + 1
                for _ in range(k - 1):
                    q = self.ends[q]
                return -1 - q
            prev, v, side = last
            i = self.i[v - self.f]
            if side == INNER:
                k += i - 1
            elif k == i:
                return self._down(prev, v, INNER)
            elif k > i:
                k += self.rank[self.y[v - self.f]] - 1
            chain = prev

    def outer_part(self, chain, rule: int):
        """The chain of the outer symbol of the rule that stands at the end of ``chain``."""
        return self._down(chain, rule, OUTER)

    def roots(self) -> list:
        """The node at the root of each document (a null if it is empty)."""
        return [self._root(-1 - p) for p in self.g.doc_start[:-1].tolist()]

    def label(self, node) -> int:
        return self.symbol(node)

    def _real(self, chain):
        node = self._root(chain)
        return node if self.label(node) < self.g.n_labels else None

    def first_child(self, node):
        return self._real(self.at_hole(node, 1))

    def next_sibling(self, node):
        return self._real(self.at_hole(node, 2))

    def binary_parent(self, node):
        """The node of which this one is first child (1) or next sibling (2), and which; None at a root."""
        chain = node
        while True:
            last = self._last(chain)
            if last is None:
                p, k = self.up[-1 - chain]
                if p < 0:
                    return None
                return self._owner(-1 - p, k)
            prev, v, side = last
            if side == INNER:
                return self._owner(self._down(prev, v, OUTER), self.i[v - self.f])
            chain = prev

    def _owner(self, chain, k: int):
        """The label that owns hole k of the symbol at the end of ``chain``, and the number of its own hole."""
        s = self.symbol(chain)
        while s >= self.f:
            i, r = self.i[s - self.f], self.rank[self.y[s - self.f]]
            if k < i or k >= i + r:
                k = k if k < i else k - r + 1
                chain, s = self._down(chain, s, OUTER), self.x[s - self.f]
            else:
                k -= i - 1
                chain, s = self._down(chain, s, INNER), self.y[s - self.f]
        return chain, k

    def parent(self, node):
        got = self.binary_parent(node)
        while got is not None and got[1] == 2:
            got = self.binary_parent(got[0])
        return None if got is None else got[0]

    # Whole traversals

    def traverse(self, root, order: str = "dflr", mode: str = "rec") -> tuple[int, int]:
        """Visited nodes and a checksum of their order: ``rec`` keeps the nodes to return to, ``iter`` finds its way by parents."""
        n = check = 0
        hashes = [zlib.crc32(name.encode()) + kind for kind, name in self.g.names]
        if self.label(root) >= self.g.n_labels:
            return 0, 0
        first, second = (self.first_child, self.next_sibling) if order == "dflr" else (self.next_sibling, self.first_child)
        one = 1 if order == "dflr" else 2
        if mode == "rec":
            stack = [root]
            while stack:
                node = stack.pop()
                n += 1
                check = (check + n * hashes[self.label(node)]) % (1 << 61)
                stack += [x for x in (second(node), first(node)) if x is not None]
            return n, check
        node = root
        while node is not None:
            n += 1
            check = (check + n * hashes[self.label(node)]) % (1 << 61)
            new = first(node)
            if new is None:
                new = second(node)
            while new is None:
                up = self.binary_parent(node)
                if up is None:
                    break
                node = up[0]
                if up[1] == one:
                    new = second(node)
            node = new
        return n, check

    # Jumps to labels

    def _search(self, chain, label: int):
        """The first node with the label in the binary subtree at ``chain``; symbols that do not generate it are jumped."""
        word, bit = label >> 6, 1 << (label & 63)
        masks = self.g.masks()
        stack = [chain]
        while stack:
            c = stack.pop()
            s = self.symbol(c)
            if s == label:
                return c
            if s >= self.f and int(masks[s, word]) & bit:
                stack.append(self._down(c, s, OUTER))
                continue
            stack += [self.at_hole(c, k) for k in range(self.rank[s], 0, -1)]
        return None

    def tagged_desc(self, node, label: int):
        """The first descendant with the label."""
        return self._search(self.at_hole(node, 1), label)

    def tagged_foll(self, node, label: int):
        """The first node with the label after the node's subtree."""
        while node is not None:
            got = self._search(self.at_hole(node, 2), label)
            if got is not None:
                return got
            node = self.parent(node)
        return None

    def locate(self, doc: int, pre: int):
        """The element with a pre-order number: stretches that end before it are passed by their totals."""
        total, want = self.g.chunks("elem").sum(axis=1), pre
        work = [-1 - int(self.g.doc_start[doc])]
        while work:
            c = work.pop()
            s = self.symbol(c)
            if s >= self.f:
                if self.rank[s] == 0 and want >= total[s]:
                    want -= int(total[s])
                else:
                    work.append(self._down(c, s, OUTER))
                continue
            if s < self.g.n_labels and self.g.names[s][0] == 0:
                if want == 0:
                    return c
                want -= 1
            work += [self.at_hole(c, k) for k in range(self.rank[s], 0, -1)]
        return None
