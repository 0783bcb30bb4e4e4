"""Baselines: the plain structure tree as balanced parentheses and as pointers, with the moves of the grammar cursor."""

from __future__ import annotations

import zlib

import numpy as np

_BLOCK = 64


class PointerTree:
    """First child, next sibling and parent as three arrays."""

    def __init__(self, events: np.ndarray, names: list[tuple[int, str]]):
        self.names = names
        at = np.flatnonzero(events >= 0)
        self.labels = events[at].tolist()
        n = len(at)
        self.fc, self.ns, self.up, self.side = [-1] * n, [-1] * n, [-1] * n, [0] * n
        stack: list[list[int]] = [[-1, -1]]
        k = 0
        for e in events.tolist():
            if e >= 0:
                top = stack[-1]
                if top[1] >= 0:
                    self.ns[top[1]], self.up[k], self.side[k] = k, top[1], 2
                elif top[0] >= 0:
                    self.fc[top[0]], self.up[k], self.side[k] = k, top[0], 1
                top[1] = k
                stack.append([k, -1])
                k += 1
            else:
                stack.pop()

    def label(self, v: int) -> int:
        return self.labels[v]

    def first_child(self, v: int):
        return self.fc[v] if self.fc[v] >= 0 else None

    def next_sibling(self, v: int):
        return self.ns[v] if self.ns[v] >= 0 else None

    def binary_parent(self, v: int):
        return (self.up[v], self.side[v]) if self.up[v] >= 0 else None

    def bytes(self) -> int:
        return 3 * 4 * len(self.labels) + 4 * len(self.labels)


class SuccinctTree:
    """Two bits a node and a label list; matching parentheses are found block by block over minimum depths."""

    def __init__(self, events: np.ndarray, names: list[tuple[int, str]]):
        self.names = names
        self.open = events >= 0
        self.labels = events[self.open].tolist()
        self.rank = (np.cumsum(self.open) - 1).tolist()
        depth = np.cumsum(np.where(self.open, 1, -1))
        pad = -len(depth) % _BLOCK
        self.depth = depth.tolist()
        filled = np.concatenate([depth, np.full(pad, depth[-1] if len(depth) else 0)])
        self.least = filled.reshape(-1, _BLOCK).min(axis=1).tolist() if len(filled) else []
        self.is_open = self.open.tolist()

    def label(self, v: int) -> int:
        return self.labels[self.rank[v]]

    def find_close(self, v: int) -> int:
        want, d = self.depth[v] - 1, self.depth
        k, n = v + 1, len(d)
        while k < n:
            if k % _BLOCK == 0 and self.least[k // _BLOCK] > want:
                k += _BLOCK
            elif d[k] == want:
                return k
            else:
                k += 1
        raise ValueError("unbalanced")

    def enclose(self, v: int):
        """The opening parenthesis around v, or None."""
        want, d = self.depth[v] - 2, self.depth
        k = v - 1
        while k >= 0:
            if k % _BLOCK == _BLOCK - 1 and self.least[k // _BLOCK] > want:
                k -= _BLOCK
            elif d[k] == want:
                break
            else:
                k -= 1
        return k + 1 if want >= 0 else None

    def first_child(self, v: int):
        return v + 1 if self.is_open[v + 1] else None

    def next_sibling(self, v: int):
        k = self.find_close(v) + 1
        return k if k < len(self.is_open) and self.is_open[k] else None

    def binary_parent(self, v: int):
        if v == 0:
            return None
        if self.is_open[v - 1]:
            return v - 1, 1
        # The sibling before: its closing parenthesis stands right before v.
        want, d = self.depth[v - 1] + 1, self.depth
        k = v - 2
        while k >= 0 and not (d[k] == want and self.is_open[k] and (k == 0 or d[k - 1] == want - 1)):
            if k % _BLOCK == _BLOCK - 1 and self.least[k // _BLOCK] > want:
                k -= _BLOCK
            else:
                k -= 1
        return k, 2

    def bytes(self) -> int:
        return (2 * len(self.labels) + 7) // 8 + 4 * len(self.least) + 4 * len(self.labels)


def traverse(tree, root: int, order: str = "dflr", mode: str = "rec") -> tuple[int, int]:
    """As the grammar cursor: visited nodes and a checksum of their order."""
    hashes = [zlib.crc32(name.encode()) + kind for kind, name in tree.names]
    first, second = (tree.first_child, tree.next_sibling) if order == "dflr" else (tree.next_sibling, tree.first_child)
    one = 1 if order == "dflr" else 2
    n = check = 0
    if mode == "rec":
        stack = [root]
        while stack:
            v = stack.pop()
            n += 1
            check = (check + n * hashes[tree.label(v)]) % (1 << 61)
            stack += [x for x in (second(v), first(v)) if x is not None]
        return n, check
    v = root
    while v is not None:
        n += 1
        check = (check + n * hashes[tree.label(v)]) % (1 << 61)
        new = first(v)
        new = second(v) if new is None else new
        while new is None:
            up = tree.binary_parent(v)
            if up is None:
                break
            v = up[0]
            if up[1] == one:
                new = second(v)
        v = new
    return n, check


def structures(events: np.ndarray, names: list[tuple[int, str]], max_rank: int = 2) -> dict[str, tuple[object, int, int]]:
    """The traversal structures of one document: cursor, root and bytes of grammars by compressor, and of the plain trees."""
    from treegrammar.grammar.compress import COMPRESSORS, no_start_rule
    from treegrammar.measure import model_bytes
    from treegrammar.views.nodewise import Cursor

    doc_start = np.array([0, len(events)], np.int64)
    grammars = {name: COMPRESSORS[name](names, events, doc_start) for name in ("pairs", "patterns", "dag", "one_rule")}
    grammars["no_start"] = no_start_rule(grammars["pairs"])
    out: dict[str, tuple[object, int, int]] = {}
    for name, g in grammars.items():
        s = model_bytes(g.n_rules, len(g.start), g.n_labels)
        c = Cursor(g)
        out[name] = (c, c.roots()[0], int(s["rules_bytes"] + s["tag_bytes"] + s["ex_bytes"]))
    for name, tree in (("succinct", SuccinctTree(events, names)), ("pointer", PointerTree(events, names))):
        out[name] = (tree, 0, tree.bytes())
    return out
