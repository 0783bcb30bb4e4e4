"""The start's shape as balanced parentheses, with the end of a subtree found by block minima."""

from __future__ import annotations

import numpy as np

from treegrammar.grammar.model import Grammar

BLOCK = 128


class ParenthesisShape:
    """Answers ``shape[k]``, the position after the subtree of the k-th start node, from 2 bits a node and a block directory."""

    def __init__(self, packed: bytes, nodes: int):
        self.bits = np.unpackbits(np.frombuffer(packed, np.uint8), count=2 * nodes, bitorder="little").astype(bool)
        self.place = np.flatnonzero(self.bits)
        self.opened = np.cumsum(self.bits)
        depth = np.cumsum(np.where(self.bits, 1, -1))
        pad = -len(depth) % BLOCK
        self.depth = depth
        self.least = np.concatenate([depth, np.full(pad, depth[-1] if len(depth) else 0)]).reshape(-1, BLOCK).min(axis=1) if len(depth) else np.empty(0, int)

    def __getitem__(self, k: int) -> int:
        at = int(self.place[k])
        want = int(self.depth[at]) - 1
        block = at // BLOCK
        part = np.flatnonzero(self.depth[at + 1 : (block + 1) * BLOCK] <= want)
        if not len(part):
            block += 1 + int(np.argmax(self.least[block + 1 :] <= want))
            close = block * BLOCK + int(np.flatnonzero(self.depth[block * BLOCK : (block + 1) * BLOCK] <= want)[0])
        else:
            close = at + 1 + int(part[0])
        return int(self.opened[close])

    def bytes(self) -> int:
        return len(self.bits) // 8 + 4 * len(self.least)


def with_parentheses(g: Grammar, packed: bytes) -> Grammar:
    """The grammar with its explicit shape table replaced by the succinct one."""
    g.tables["ends"] = ParenthesisShape(packed, len(g.start))
    return g
