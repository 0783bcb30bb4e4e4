"""The chunk-wise view: node numbers and serialized subtrees of selected nodes, without expanding the grammar.

A symbol of rank k has k + 1 stretches between its holes. What a symbol contributes in a state (selected positions, or
tags and results) is worked out once as stretches with relative offsets and copied wherever the symbol occurs again; a
walk over the start adds the bases. Text and element totals of stretches come from the chunk tables, also where
nothing is output, so numbers stay right across jumped parts.
"""

from __future__ import annotations

from html import escape

import numpy as np

from treegrammar.grammar.model import splice_chunks
from treegrammar.views.rulewise import Run

_NONE = np.empty(0, np.int64)
_NO_TAGS = np.empty(0, np.int32)
#: Rows of a position array: elements, structure nodes, and texts before it.
E_, N_, T_ = 0, 1, 2


class Chunkwise:
    def __init__(self, run: Run, copy: bool = True, start_skip: bool = True, lazy: bool = False):
        self.run, self.g, self.copy, self.start_skip, self.lazy = run, run.g, copy, start_skip, lazy
        if not lazy:
            self.cnt, self.hole = run.tables()
        self.size = np.stack([self.g.chunks(k) for k in ("elem", "node", "text")], axis=2)  # (symbols, stretches, 3)
        self._selected: dict[tuple[int, int], list[np.ndarray]] = {}
        self._output: dict[tuple[int, int, bool], list[tuple]] = {}

    # Selected positions

    def _counted(self, v: int, q: int) -> int:
        """Selected nodes of v in state q: from the tables, or worked out (or jumped over) when first asked for."""
        return self.run.behaviour(v, q)[0] if self.lazy else self.cnt[v, q]

    def _below(self, v: int, q: int, i: int) -> int:
        """The state at hole i of v entered in state q."""
        return self.run.behaviour(v, q)[1][i] if self.lazy else int(self.hole[v, q, i])

    def selected(self, v: int, q: int) -> list[np.ndarray]:
        """Per stretch of v in state q, the relative positions (3, n) of selected nodes."""
        g, memo = self.g, self._selected
        work = [(v, q)]
        while work:
            s, p = work[-1]
            if (s, p) in memo:
                work.pop()
                continue
            r = int(g.rank[s])
            if not self._counted(s, p):
                memo[s, p] = [np.empty((3, 0), np.int64)] * (r + 1)
            elif s < g.n_labels:
                memo[s, p] = [np.zeros((3, 1), np.int64), np.empty((3, 0), np.int64), np.empty((3, 0), np.int64)]
            else:
                k = s - g.first_rule
                x, i, y = int(g.outer[k]), int(g.hole[k]), int(g.inner[k])
                below = self._below(x, p, i - 1)
                need = [key for key in ((x, p), (y, below)) if key not in memo]
                if need:
                    work += need
                    continue
                a = list(zip(memo[x, p], self.size[x], strict=False))
                b = list(zip(memo[y, below], self.size[y], strict=False))
                memo[s, p] = [part[0] for part in splice_chunks(a[: int(g.rank[x]) + 1], i, b[: int(g.rank[y]) + 1], _join_positions)]
            work.pop()
        if not self.lazy:
            self.run.count.visited = len(memo)
        return memo[v, q]

    def materialize(self, state: int | None = None, limit: int | None = None) -> tuple[list[np.ndarray], int]:
        """Per document the positions (3, n) of selected nodes, and the state at the open end; stops after ``limit`` nodes."""
        g = self.g
        out, exit_, found = [], self.run.a.initial if state is None else state, 0
        ends, start, bounds = g.start_ends(), g.start.tolist(), g.doc_start.tolist()
        skips = np.stack([g.start_skips(k) for k in ("elem", "node", "text")], axis=1) if self.start_skip else None
        u = self.run.a.universal
        for d in range(len(bounds) - 1):
            base, parts = np.zeros(3, np.int64), []
            pending: list[tuple[int, int, int]] = []  # symbol, state, next stretch
            states = [self.run.a.initial if state is None else state]
            k = bounds[d]
            last = d == len(bounds) - 2
            while k < bounds[d + 1] and (limit is None or found < limit):
                s, q = start[k], states.pop()
                if s == g.end:
                    exit_ = q
                if skips is not None and q == u and self.run.skip and not (g.open_end and last):
                    base = base + skips[k]
                    k = int(ends[k])
                else:
                    pending.append((s, q, 0))
                    k += 1
                while pending:
                    s, q, c = pending[-1]
                    if self._counted(s, q):
                        got = self.selected(s, q)[c]
                        if got.shape[1]:
                            parts.append(got + base[:, None])
                            found += got.shape[1]
                    base = base + self.size[s, c]
                    if c < g.rank[s]:
                        pending[-1] = (s, q, c + 1)
                        states.append(self._below(s, q, c))
                        break
                    pending.pop()
            got = np.concatenate(parts, axis=1) if parts else np.empty((3, 0), np.int64)
            out.append(got if limit is None else got[:, :limit])
        return out, exit_

    # Output

    def inside_holes(self) -> np.ndarray:
        """(symbols, states, max_rank): whether a hole lies below a node that is selected inside the symbol."""
        if not hasattr(self, "_inside"):
            g, m, w = self.g, self.run.a.n_states, self.g.max_rank
            out = np.zeros((g.first_rule + g.n_rules, m, w), bool)
            out[: g.n_labels, :, 0] = self.run.label_selects.T
            from_inner, index = g.splice()
            for rules in g.levels():
                x, y, i = g.outer[rules], g.inner[rules], g.hole[rules] - 1
                at = np.broadcast_to(i[:, None, None], (len(rules), m, 1))
                below = np.take_along_axis(self.hole[x], at, 2)[..., 0]
                own = np.take_along_axis(out[x], at, 2)
                idx = np.broadcast_to(index[rules][:, None, :], (len(rules), m, w))
                out[g.first_rule + rules] = np.where(from_inner[rules][:, None, :], np.take_along_axis(out[y[:, None], below], idx, 2) | own, np.take_along_axis(out[x], idx, 2))
            self._inside = out
        return self._inside

    def output(self, v: int, q: int, inside: bool) -> list[tuple]:
        """Per stretch: tags, and results (4, n): place in the tags, then elements, nodes and texts before."""
        g, memo, ins = self.g, self._output, self.inside_holes()
        work = [(v, q, inside)]
        while work:
            s, p, w = work[-1]
            if (s, p, w) in memo:
                self.run.count.memo_hits += 1
                work.pop()
                continue
            r = int(g.rank[s])
            none = (_NO_TAGS, np.empty((4, 0), np.int64))
            if not w and not self.cnt[s, p] or s >= g.n_labels and s < g.first_rule:
                memo[s, p, w] = [none] * (r + 1)
            elif s < g.n_labels:
                hit = bool(self.run.label_selects[p, s])
                shown = hit or w
                memo[s, p, w] = [
                    (np.array([s], np.int32) if shown else _NO_TAGS, np.zeros((4, int(hit)), np.int64)), (np.array([-1], np.int32) if shown else _NO_TAGS, np.empty((4, 0), np.int64)), none,
                ]
            else:
                k = s - g.first_rule
                x, i, y = int(g.outer[k]), int(g.hole[k]), int(g.inner[k])
                below, deep = int(self.hole[x, p, i - 1]), w or bool(ins[x, p, i - 1])
                need = [key for key in ((x, p, w), (y, below, deep)) if key not in memo]
                if need:
                    work += need
                    continue
                a = [(c, self.size[x, j]) for j, c in enumerate(memo[x, p, w])]
                b = [(c, self.size[y, j]) for j, c in enumerate(memo[y, below, deep])]
                memo[s, p, w] = [part[0] for part in splice_chunks(a, i, b, _join_output)]
            work.pop()
        return memo[v, q, inside]

    def serialize(self, texts: list[str], doc_texts: list[int], state: int | None = None, inside: bool = False):
        """Per document: tags, results (4, n) and the first text; then the state at the open end."""
        g, ins = self.g, self.inside_holes()
        q0 = self.run.a.initial if state is None else state
        out, exit_ = [], q0
        start, bounds, ends = g.start.tolist(), g.doc_start.tolist(), g.start_ends()
        skips = np.stack([g.start_skips(k) for k in ("elem", "node", "text")], axis=1) if self.start_skip else None
        u = self.run.a.universal
        for d in range(len(bounds) - 1):
            base, at, tags, results = np.zeros(3, np.int64), 0, [], []
            pending: list[tuple[int, int, bool, int]] = []
            states = [(q0, inside)]
            k, last = bounds[d], d == len(bounds) - 2
            while k < bounds[d + 1]:
                s, (q, w) = start[k], states.pop()
                if s == g.end:
                    exit_ = q
                if skips is not None and q == u and not w and self.run.skip and not (g.open_end and last):
                    base = base + skips[k]
                    k = int(ends[k])
                else:
                    pending.append((s, q, w, 0))
                    k += 1
                while pending:
                    s, q, w, c = pending[-1]
                    if w or self.cnt[s, q]:
                        new, res = self.output(s, q, w)[c]
                        if len(new):
                            tags.append(new)
                        if res.shape[1]:
                            results.append(res + np.array([at, *base])[:, None])
                        at += len(new)
                    base = base + self.size[s, c]
                    if c < g.rank[s]:
                        pending[-1] = (s, q, w, c + 1)
                        states.append((int(self.hole[s, q, c]), w or bool(ins[s, q, c])))
                        break
                    pending.pop()
                if not self.copy:
                    self._output.clear()
            self.run.count.copied += at
            out.append((np.concatenate(tags) if tags else _NO_TAGS, np.concatenate(results, axis=1) if results else np.empty((4, 0), np.int64)))
        return out, exit_


def _join_positions(parts):
    base, got = np.zeros(3, np.int64), []
    for p, size in parts:
        got.append(p + base[:, None])
        base = base + size
    return np.concatenate(got, axis=1), base


def _join_output(parts):
    base, at, tags, results = np.zeros(3, np.int64), 0, [], []
    for (t, r), size in parts:
        tags.append(t)
        results.append(r + np.array([at, *base])[:, None])
        at += len(t)
        base = base + size
    return (np.concatenate(tags), np.concatenate(results, axis=1)), base


def subtree_ends(tags: np.ndarray, places: np.ndarray) -> np.ndarray:
    """For the opening tags at ``places`` the position after their closing tag."""
    is_open = tags >= 0
    depth = np.cumsum(np.where(is_open, 1, -1))
    order = np.lexsort((np.arange(len(tags)), np.where(is_open, depth, depth + 1)))
    opens, closes = order[is_open[order]], order[~is_open[order]]
    end = np.zeros(len(tags), np.int64)
    end[opens] = closes + 1
    return end[places]


_TEXT, _VALUE = 0, 1


def template(tags: list[int], names: list[tuple[int, str]]) -> list[str | int]:
    """Markup of a stretch of tags as literals and places for texts and attribute values."""
    out: list[str | int] = []
    literal: list[str] = []
    stack: list[str | None] = []
    open_ = False

    def place(kind: int) -> None:
        out.append("".join(literal))
        out.append(kind)
        literal.clear()

    for e in tags:
        if e >= 0:
            kind, name = names[e]
            if kind == 0:
                literal.append(("><" if open_ else "<") + name)
                open_ = True
                stack.append(name)
                continue
            if kind == 1:
                if open_:
                    literal.append(">")
                    open_ = False
                place(_TEXT)
            elif kind == 4:
                literal.append(f' {name[1:]}="')
            elif kind == 3:
                place(_VALUE)
                literal.append('"')
            stack.append(None)
        else:
            name = stack.pop() if stack else None
            if name is not None:
                literal.append("/>" if open_ else f"</{name}>")
                open_ = False
    out.append("".join(literal))
    if tags and names[tags[0]][0] in (2, 4):
        out[0] = out[0].lstrip(" ")
    return out


def fill(parts: list[str | int], texts: list[str], first_text: int) -> str:
    """A template with its texts, taken in order from ``first_text``."""
    out, t = [], first_text
    for p in parts:
        if p.__class__ is str:
            out.append(p)
        else:
            value = texts[t]
            t += 1
            if "&" in value or "<" in value or ">" in value or p == _VALUE and ('"' in value or "'" in value):
                value = escape(value, quote=p == _VALUE)
            out.append(value)
    return "".join(out)


def render(tags: list[int], names: list[tuple[int, str]], texts: list[str], first_text: int) -> str:
    return fill(template(tags, names), texts, first_text)


class Renderer:
    """Renders stretches of tags; short ones that come again share their template."""

    SHORT, MOST = 96, 20_000

    def __init__(self, names: list[tuple[int, str]], texts: list[str]):
        self.names, self.texts, self.known = names, texts, {}

    def __call__(self, tags: np.ndarray, begin: int, end: int, first_text: int) -> str:
        own = tags[begin:end]
        if end - begin > self.SHORT:
            return fill(template(own.tolist(), self.names), self.texts, first_text)
        key = own.tobytes()
        parts = self.known.get(key)
        if parts is None:
            if len(self.known) > self.MOST:
                self.known.clear()
            parts = self.known[key] = template(own.tolist(), self.names)
        return fill(parts, self.texts, first_text)
