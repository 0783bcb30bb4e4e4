"""Paths as deterministic top-down automata that select nodes of first-child/next-sibling trees.

A state is a set of steps that the nodes of a sibling list may match next. It is pruned: once a descendant step waits,
earlier steps add nothing. The automaton is determinised before evaluation over the label classes of the query (or step by step,
as ``lazy``), then minimised by partition refinement.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from treegrammar.xpath.parse import CHILD, DESCENDANT, FOLLOWING, Step, UnsupportedPathError, parse_path


class AutomatonLimitError(ValueError):
    """Determinising would need more states than allowed."""


def transition(steps: list[Step], state: tuple[int, ...], hits: tuple[bool, ...], prune: bool = True) -> tuple[bool, tuple[int, ...], tuple[int, ...]]:
    """Whether a node that matches the tests ``hits`` is selected in ``state``, and the states of its children list and of the nodes after it."""
    down, right, selects = set(), set(state), False
    for i in state:
        if steps[i].axis == DESCENDANT:
            down.add(i)
        if hits[i]:
            if i + 1 == len(steps):
                selects = True
            elif steps[i + 1].axis == FOLLOWING:
                right.add(i + 1)
            else:
                down.add(i + 1)
    return selects, _tidy(steps, down, prune), _tidy(steps, right, prune)


def _tidy(steps: list[Step], state: set[int], prune: bool) -> tuple[int, ...]:
    if prune:
        waiting = max((i for i in state if steps[i].axis == DESCENDANT), default=-1)
        state = {i for i in state if i >= waiting}
    return tuple(sorted(state))


@dataclass
class Automaton:
    """Tables over states and label classes; class numbers come from ``classify``."""

    steps: list[Step]
    classes: list[tuple[int, str | None]]  # kind and name; None: any other label of the kind
    selects: np.ndarray  # (states, classes)
    to_down: np.ndarray
    to_right: np.ndarray
    initial: int
    universal: int  # the state in which nothing below or after is selected, -1 if there is none

    @property
    def n_states(self) -> int:
        return len(self.selects)

    def classify(self, names: list[tuple[int, str]]) -> np.ndarray:
        where = {c: k for k, c in enumerate(self.classes)}
        return np.array([where.get((k, n), where[(k, None)]) for k, n in names], np.int64).reshape(-1)

    def relevance(self, fine: bool = True) -> tuple[np.ndarray, np.ndarray]:
        """(states, classes) whether a label matters in a state, and for each state what holes get otherwise:
        0 all keep the state, 1 all become universal, 2 only the last one keeps it and only on the spine."""
        m, c = self.selects.shape
        q = np.arange(m)[:, None]
        keeps = (self.to_down == q) & (self.to_right == q) & ~self.selects
        if not fine:
            return ~keeps, np.zeros(m, np.int64)
        u = self.universal
        dies = (self.to_down == u) & (self.to_right == u) & ~self.selects & (u >= 0)
        right = (self.to_down == u) & (self.to_right == q) & ~self.selects & (u >= 0) & (q != u)
        options = np.stack([keeps, dies, right])
        best = np.argmax(options.sum(axis=2), axis=0)
        return ~options[best, np.arange(m)], best

    def rows(self) -> list[tuple]:
        """state, kind, label (null: any other), selects, to_fc, to_ns."""
        return [(s, k, n, bool(self.selects[s, j]), int(self.to_down[s, j]), int(self.to_right[s, j])) for s in range(self.n_states) for j, (k, n) in enumerate(self.classes)]


def label_classes(steps: list[Step]) -> list[tuple[int, str | None]]:
    named = {(0 if s.kind == "element" else 4, s.name) for s in steps if s.name is not None}
    return sorted(named) + [(k, None) for k in range(5)]


def compile_path(path: str | list[Step], prune: bool = True, minimise: bool = True, max_states: int = 4096) -> Automaton:
    steps = parse_path(path) if isinstance(path, str) else path
    classes = label_classes(steps)
    hits = [tuple(s.matches(k, n if n is not None else "\0other") for s in steps) for k, n in classes]
    start = (0,)
    number, queue = {start: 0}, [start]
    selects, down, right = [], [], []
    for state in queue:
        row = [transition(steps, state, h, prune) for h in hits]
        for _, a, b in row:
            for x in (a, b):
                if x not in number:
                    if len(number) >= max_states:
                        raise AutomatonLimitError(f"more than {max_states} states; evaluate lazily or raise the limit")
                    number[x] = len(queue)
                    queue.append(x)
        selects.append([r[0] for r in row])
        down.append([number[r[1]] for r in row])
        right.append([number[r[2]] for r in row])
    s, d, r = np.array(selects), np.array(down), np.array(right)
    group = np.zeros(len(queue), np.int64)
    if minimise:
        while True:
            key = np.concatenate([group[:, None], s, group[d], group[r]], axis=1)
            _, new = np.unique(key, axis=0, return_inverse=True)
            new = new.reshape(-1)
            if new.max() == group.max():
                break
            group = new
        order = list(dict.fromkeys(group.tolist()))
        rank = {g: k for k, g in enumerate(order)}
        group = np.array([rank[g] for g in group.tolist()])
        first = [int(np.flatnonzero(group == k)[0]) for k in range(len(order))]
        s, d, r = s[first], group[d[first]], group[r[first]]
        start_state = int(group[0])
    else:
        start_state = 0
    q = np.arange(len(s))[:, None]
    dead = np.flatnonzero(((d == q) & (r == q) & ~s).all(axis=1))
    return Automaton(steps, classes, s, d, r, start_state, int(dead[0]) if len(dead) else -1)


def has_following(path: str) -> bool:
    return any(s.axis == FOLLOWING for s in parse_path(path))


__all__ = ["CHILD", "DESCENDANT", "FOLLOWING", "Automaton", "AutomatonLimitError", "Step", "UnsupportedPathError", "compile_path", "has_following", "parse_path", "transition"]
