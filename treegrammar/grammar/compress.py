"""Compressors: pair replacement, shared subtrees, bounded-pattern search, the trivial grammars, and rank reduction.

Every compressor returns rules that are in binary normal form already, so the conversion is the identity except for
pruned grammars. Pair replacement is vectorised: a round counts all (outer, hole, inner) triples at once, takes the most frequent
compatible ones, and contracts their edges together.
"""

from __future__ import annotations

import numpy as np

from treegrammar.grammar.model import Grammar, ranked_tree


class Tree:
    """A mutable forest of ranked symbols: children by slot, parents, and the rules made so far."""

    def __init__(self, names: list[tuple[int, str]], events: np.ndarray, doc_start: np.ndarray, open_end: bool, max_rank: int):
        self.names, self.open_end, self.max_rank = names, open_end, max_rank
        self.sym, self.parent, self.slot = ranked_tree(events, doc_start, len(names), open_end)
        n = len(self.sym)
        self.width = max(2, max_rank)
        self.child = np.full((n, self.width), -1, np.int64)
        at = np.flatnonzero(self.parent >= 0)
        self.child[self.parent[at], self.slot[at]] = at
        self.alive = np.ones(n, bool)
        self.rank: list[int] = [2] * len(names) + [0, 0]
        self.rules: list[tuple[int, int, int]] = []
        self.made: dict[tuple[int, int, int], int] = {}
        self.end = len(names) + 1
        self._ranks = np.empty(0, np.int64)

    def ranks(self) -> np.ndarray:
        """The rank of every symbol made so far."""
        done = len(self._ranks)
        if done < len(self.rank):
            self._ranks = np.concatenate([self._ranks, np.array(self.rank[done:], np.int64)])
        return self._ranks

    def rule(self, x: int, i: int, y: int) -> int:
        key = (x, i, y)
        got = self.made.get(key)
        if got is None:
            got = self.made[key] = len(self.rank)
            self.rank.append(self.rank[x] + self.rank[y] - 1)
            self.rules.append(key)
        return got

    def edges(self) -> tuple[np.ndarray, np.ndarray]:
        """Inner nodes whose contraction respects the rank bound, and the key of the triple."""
        v = np.flatnonzero(self.alive & (self.parent >= 0) & (self.sym != self.end))
        u = self.parent[v]
        rank = self.ranks()
        v = v[rank[self.sym[u]] + rank[self.sym[v]] - 1 <= self.max_rank]
        u = self.parent[v]
        return v, self.sym[u] << 33 | self.slot[v] << 29 | self.sym[v]

    def contract(self, v: np.ndarray, x: int, i: int, y: int) -> int:
        """Replace the edges to the nodes v, all of one triple (slot i from 0), by the rule's symbol."""
        z = self.rule(x, i + 1, y)
        self.splice(v, self.rank[x], i, self.rank[y], z)
        return z

    def splice(self, v: np.ndarray, rx: int, i: int, ry: int, z: int | np.ndarray) -> None:
        """Put the children of the nodes v, of rank ry, in their place at slot i of the nodes above, of rank rx, which become z."""
        u = self.parent[v]
        new = np.concatenate([self.child[u, :i], self.child[v, :ry], self.child[u, i + 1 : rx]], axis=1)
        self.child[u, : new.shape[1]] = new
        self.child[u, new.shape[1] :] = -1
        for k in range(new.shape[1]):
            self.parent[new[:, k]], self.slot[new[:, k]] = u, k
        self.sym[u] = z
        self.alive[v] = False

    def around(self, u: np.ndarray) -> np.ndarray:
        """The nodes u and their children: those whose triples change when edges below u are contracted."""
        below = self.child[u]
        return np.concatenate([u, below[below >= 0]])

    def alternate(self, v: np.ndarray) -> np.ndarray:
        """Of edges of a triple with equal symbols, those at odd places of their chains, counted from the top."""
        where = np.full(len(self.sym), -1, np.int64)
        where[v] = np.arange(len(v))
        up = where[self.parent[v]]  # the edge above in the chain
        dist, jump = (up >= 0).astype(np.int64), up.copy()
        while (jump >= 0).any():
            m = jump >= 0
            dist[m] += dist[jump[m]]
            jump[m] = jump[jump[m]]
        return v[dist % 2 == 0]

    def grammar(self) -> Grammar:
        at = np.flatnonzero(self.alive)
        roots = np.flatnonzero(self.parent[at] < 0)
        r = np.array(self.rules, np.int64).reshape(-1, 3)
        return Grammar(self.names, r[:, 0], r[:, 1], r[:, 2], np.array(self.rank, np.int64), self.sym[at], np.append(roots, len(at)).astype(np.int64), self.open_end)


class Triples:
    """The triple of every edge of a tree that may be contracted, and how often each occurs, kept from round to round:
    only the edges around contracted ones are looked at again."""

    def __init__(self, tree: Tree):
        v, key = tree.edges()
        self.tree = tree
        self.key, code, self.count = np.unique(key, return_inverse=True, return_counts=True)
        self.number = {k: i for i, k in enumerate(self.key.tolist())}
        self.of = np.full(len(tree.sym), -1, np.int32)
        self.of[v] = code
        self.live = np.flatnonzero(tree.alive)
        self.mark = np.zeros(len(tree.sym), bool)

    def most(self, limit: int) -> list[tuple[int, int, int]]:
        """(count, key, number) of the most frequent triples, down to a quarter of the first; ties go to the smaller key."""
        top = int(self.count.max(initial=0))
        at = np.flatnonzero(self.count >= max(2, top // 4))
        at = at[np.lexsort((self.key[at], -self.count[at]))][:limit]
        return list(zip(self.count[at].tolist(), self.key[at].tolist(), at.tolist(), strict=True))

    def nodes(self, numbers: list[int]) -> list[np.ndarray]:
        """The inner nodes of the edges of each of some triples, in pre-order."""
        if 2 * np.count_nonzero(self.tree.alive) < len(self.live):
            self.live = self.live[self.tree.alive[self.live]]
        place = np.zeros(len(self.key) + 1, np.int16)  # the last entry is that of edges without a triple
        place[numbers] = np.arange(1, len(numbers) + 1)
        got = place[self.of[self.live]]
        at = np.flatnonzero(got)
        got = got[at]
        at = at[np.argsort(got, kind="stable")]
        return np.split(self.live[at], np.cumsum(np.bincount(got, minlength=len(numbers) + 1)[1:])[:-1])

    def edges(self) -> tuple[np.ndarray, np.ndarray]:
        """The inner nodes of all edges that have a triple, in pre-order, and its number."""
        v = np.flatnonzero(self.of >= 0)
        return v, self.of[v]

    def update(self, changed: np.ndarray) -> None:
        tree, rank = self.tree, self.tree.ranks()
        self.mark[changed] = True
        v = np.flatnonzero(self.mark)
        self.mark[v] = False
        old = self.of[v]
        self.count -= np.bincount(old[old >= 0], minlength=len(self.count))
        self.of[v] = -1
        v = v[tree.alive[v] & (tree.parent[v] >= 0) & (tree.sym[v] != tree.end)]
        u = tree.parent[v]
        v = v[rank[tree.sym[u]] + rank[tree.sym[v]] - 1 <= tree.max_rank]
        key, code = np.unique(tree.sym[tree.parent[v]] << 33 | tree.slot[v] << 29 | tree.sym[v], return_inverse=True)
        number = self.number
        at = np.array([number.setdefault(k, len(number)) for k in key.tolist()], np.int64)
        new = at >= len(self.key)
        self.key = np.concatenate([self.key, key[new]])
        self.of[v] = at[code]
        self.count = np.bincount(at[code], minlength=len(self.key)) + np.concatenate([self.count, np.zeros(int(new.sum()), np.int64)])


def pairs(names, events, doc_start, open_end=False, max_rank: int = 2, batch: int = 48, prune: bool = False, max_rounds: int = 400, before=None) -> Grammar:
    """Pair replacement under a rank bound; ties go to the smaller triple, so builds repeat exactly."""
    tree = Tree(names, events, doc_start, open_end, max_rank)
    if before is not None:
        before(tree)
    triples = Triples(tree)
    for _ in range(max_rounds):
        outers: set[int] = set()
        inners: set[int] = set()
        chosen = []
        for count, k, number in triples.most(8 * batch):
            if len(chosen) == batch:
                break
            x, i, y = k >> 33, k >> 29 & 15, k & (1 << 29) - 1
            z_rank = tree.rank[x] + tree.rank[y] - 1
            if count - (z_rank + 1) <= 0 and (x, i + 1, y) not in tree.made:
                continue
            if x in outers or x in inners or y in outers:
                continue
            outers.add(x)
            inners.add(y)
            chosen.append((number, x, i, y))
        if not chosen:
            break
        changed = []
        for nodes, (_, x, i, y) in zip(triples.nodes([c[0] for c in chosen]), chosen, strict=True):
            if x == y:
                nodes = tree.alternate(nodes)
            if len(nodes) > 1 or (x, i + 1, y) in tree.made:
                above = tree.parent[nodes]
                tree.contract(nodes, x, i, y)
                changed += [nodes, tree.around(above)]
        if not changed:
            break
        triples.update(np.concatenate(changed))
    g = tree.grammar()
    return pruned(g) if prune else g


def pruned(g: Grammar) -> Grammar:
    """Rules that are used once are dissolved into their user, and what is left is put back in normal form."""
    from treegrammar.grammar.normal_form import general, inline_single, normal_form

    return normal_form(inline_single(general(g)))


def dag(names, events, doc_start, open_end=False, max_rank: int = 2) -> Grammar:
    """Shared subtrees of the binary trees: a rank-0 symbol for every distinct subtree that occurs more than once."""
    tree = Tree(names, events, doc_start, open_end, 2)
    n, null = len(tree.sym), len(names)
    sym, right = tree.sym.tolist(), tree.child[:, 1].tolist()  # the left child is the next node
    number: dict[tuple[int, int, int], int] = {}
    of, past = [0] * n, list(range(1, n + 1))  # the class of a subtree, and the node after it
    first: list[int] = []
    # Nulls and the open end are numbered in front, as the last node of all is one of them.
    for s in dict.fromkeys([sym[-1], null] if n else []):
        at = np.flatnonzero(tree.sym == s)
        if len(at):
            for v in at.tolist() if first else ():
                of[v] = len(first)
            first.append(int(at[-1]))
    for v in np.flatnonzero(tree.sym < null)[::-1].tolist():
        b = right[v]
        key = (sym[v], of[v + 1], of[b])
        got = number.get(key)
        if got is None:
            got = number[key] = len(first)
            first.append(v)
        of[v] = got
        past[v] = past[b]
    classes = np.array(of, np.int64)
    count = np.bincount(classes, minlength=len(first)).tolist()
    symbol: dict[int, int] = {}
    # Subtrees with an open end or a single null are no symbols; an inner subtree counts only where its parent is not shared itself.
    above = classes[tree.parent]
    uses = (tree.parent < 0) | (np.array(first, np.int64)[above] == tree.parent) | (np.array(count)[above] < 2)
    shared_uses = np.bincount(classes[uses], minlength=len(first)).tolist()
    open_ = [False] * len(count)
    for c in range(len(count)) if open_end else ():
        v = first[c]
        open_[c] = sym[v] == tree.end or sym[v] < null and (open_[of[v + 1]] or open_[of[right[v]]])

    def closed_symbol(c: int) -> int | None:
        return symbol.get(c)

    for c in range(len(count)):
        v = first[c]
        if sym[v] == null:
            symbol[c] = null
        elif shared_uses[c] > 1 and not open_[c]:
            symbol[c] = _fold(tree, v, of, right, closed_symbol, top=True)
    starts: list[int] = []
    docs: list[int] = []
    whole = [None if open_[c] else symbol.get(c) for c in range(len(count))]
    for root in np.flatnonzero(tree.parent < 0).tolist():
        docs.append(len(starts))
        v, end = root, past[root]
        while v < end:
            z = whole[of[v]]
            if z is None:
                starts.append(sym[v])
                v += 1
            else:
                starts.append(z)
                v = past[v]
    r = np.array(tree.rules, np.int64).reshape(-1, 3)
    return Grammar(names, r[:, 0], r[:, 1], r[:, 2], np.array(tree.rank, np.int64), np.array(starts, np.int64), np.array([*docs, len(starts)], np.int64), open_end)


def _fold(tree: Tree, v: int, of, right, symbol_of, top: bool) -> int:
    """One rank-0 symbol for the subtree at v: unshared parts are folded from the leaves up."""
    order, work = [], [(v, top)]
    while work:
        u, is_top = work.pop()
        if not is_top and symbol_of(of[u]) is not None:
            continue
        order.append(u)
        work += [(k, False) for k in (u + 1, right[u]) if right[u] >= 0]
    got: dict[int, int] = {}
    for u in reversed(order):
        z = int(tree.sym[u])
        for k in (right[u], u + 1) if right[u] >= 0 else ():
            y = got[k] if k in got else symbol_of(of[k])
            z = tree.rule(z, tree.rank[z], y)
        got[u] = z
    return got[v]


def patterns(names, events, doc_start, open_end=False, max_rank: int = 8, window: int = 256, passes: int = 150) -> Grammar:
    """Bounded-pattern search: nodes are visited bottom-up, and a node with its left or right neighbour below becomes a
    pattern if the same pair was met among the last ``window`` ones; larger patterns grow from smaller ones by repeated passes."""
    tree = Tree(names, events, doc_start, open_end, max_rank)
    triples = Triples(tree)
    for _ in range(passes):
        done, changed = 0, []
        v, code = triples.edges()
        if not len(v):
            break
        # Triples that are too rare to pay off at all need no look at their distances.
        rank = tree.ranks()
        seen = np.flatnonzero((triples.count > rank[triples.key >> 33] + rank[triples.key & (1 << 29) - 1])[code])[::-1]  # bottom-up
        code = code[seen]
        order = np.argsort(code.astype(np.uint16) if len(triples.key) <= 1 << 16 else code, kind="stable")
        seen, sorted_ = seen[order], code[order]
        near = np.zeros(len(seen), bool)
        close = (sorted_[1:] == sorted_[:-1]) & (seen[:-1] - seen[1:] <= window)
        near[1:] |= close
        near[:-1] |= close
        v, sorted_ = v[seen[near]], sorted_[near]
        first = np.flatnonzero(np.concatenate([[True], sorted_[1:] != sorted_[:-1]])[: len(sorted_)])
        uniq, count = triples.key[sorted_[first]], np.diff(np.append(first, len(sorted_)))
        used: set[int] = set()
        for b in np.lexsort((uniq, -count)).tolist():
            k = int(uniq[b])
            x, i, y = k >> 33, k >> 29 & 15, k & (1 << 29) - 1
            if count[b] - (tree.rank[x] + tree.rank[y]) <= 0 or x in used or y in used:
                continue
            used |= {x, y}
            nodes = v[first[b] : first[b] + count[b]]
            nodes = tree.alternate(nodes) if x == y else nodes
            if len(nodes) > 1:
                above = tree.parent[nodes]
                tree.contract(nodes, x, i, y)
                changed += [nodes, tree.around(above)]
                done += len(nodes)
            if len(used) > 400:
                break
        if not done:
            break
        triples.update(np.concatenate(changed))
    return tree.grammar()


def one_rule(names, events, doc_start, open_end=False, max_rank: int = 2) -> Grammar:
    """No rules: the whole tree, nulls included, is the start."""
    return Tree(names, events, doc_start, open_end, max_rank).grammar()


def no_start_rule(g: Grammar, max_rank: int = 3) -> Grammar:
    """The start in normal form too: each document becomes one symbol, by contracting leaves and unary chains in rounds,
    so that the depth stays logarithmic in the size of the start."""
    tree = Tree.__new__(Tree)
    n = len(g.start)
    tree.names, tree.open_end, tree.max_rank, tree.width = g.names, g.open_end, max(max_rank, g.max_rank), max(max_rank, g.max_rank)
    tree.sym, tree.alive = g.start.copy(), np.ones(n, bool)
    tree.rank, tree.rules, tree.end = g.rank.tolist(), list(zip(g.outer.tolist(), g.hole.tolist(), g.inner.tolist(), strict=True)), g.end
    tree.made, tree._ranks = {r: g.first_rule + k for k, r in enumerate(tree.rules)}, g.rank.astype(np.int64)
    tree.parent, tree.slot, tree.child = np.full(n, -1, np.int64), np.zeros(n, np.int64), np.full((n, tree.width), -1, np.int64)
    stack: list[list[int]] = []
    for k, s in enumerate(g.start.tolist()):
        if stack:
            u = stack[-1]
            tree.parent[k], tree.slot[k], tree.child[u[0], u[1]] = u[0], u[1], k
            u[1] += 1
        stack.append([k, 0])
        while stack and stack[-1][1] == tree.rank[int(tree.sym[stack[-1][0]])]:
            stack.pop()
    while True:
        v, key = tree.edges()
        if not len(v):
            break
        rank = tree.ranks()
        # Of every node at most one edge is contracted a round: a leaf first, else every other link of unary chains.
        leaf = rank[tree.sym[v]] == 0
        unary = (rank[tree.sym[v]] == 1) | (rank[tree.sym[tree.parent[v]]] == 1)
        m = leaf | unary if not leaf.any() else leaf
        v, key = v[m], key[m]
        _, one = np.unique(tree.parent[v], return_index=True)
        v, key = v[one], key[one]
        inner = np.zeros(n, bool)
        inner[v] = True
        clash = inner[tree.parent[v]]
        if clash.any():
            odd = tree.alternate(v)
            keep = np.isin(v, odd)
            v, key = v[keep], key[keep]
            inner[:] = False
            inner[v] = True
            ok = ~inner[tree.parent[v]]
            v, key = v[ok], key[ok]
        if not len(v):
            break
        triples, which = np.unique(key, return_inverse=True)
        made = np.array([tree.rule(k >> 33, (k >> 29 & 15) + 1, k & (1 << 29) - 1) for k in triples.tolist()], np.int64)[which]
        # No node is contracted twice a round, so edges of any triples go together if their slots and ranks are the same.
        rank = tree.ranks()
        form = rank[key >> 33] << 8 | (key >> 29 & 15) << 4 | rank[key & (1 << 29) - 1]
        for k in np.unique(form).tolist():
            m = form == k
            tree.splice(v[m], k >> 8, k >> 4 & 15, k & 15, made[m])
    return tree.grammar()


def rank_one(g: Grammar) -> Grammar:
    """A grammar of rank one at most for the same tree: rules with more holes are dissolved where they are used, and what
    appears again after that is shared anew by pair replacement bounded to one hole."""
    stream = g.expand()
    # expand() ends each document with the null (or open end) that closes its list of roots.
    docs = len(g.doc_start) - 1
    sizes = g.totals("node") * 2 + 1
    ends = np.cumsum(sizes)
    drop = ends - 1
    events = np.delete(stream, drop)
    starts = np.concatenate([[0], ends - np.arange(1, docs + 1)])
    return pairs(g.names, events.astype(np.int32), starts, g.open_end, max_rank=1)


COMPRESSORS = {
    "pairs": pairs, "dag": dag, "patterns": patterns, "one_rule": one_rule,
    "no_start": lambda names, events, doc_start, open_end=False, max_rank=2: no_start_rule(pairs(names, events, doc_start, open_end, max_rank)),
    "pairs_folded": lambda names, events, doc_start, open_end=False, max_rank=2: no_start_rule(pairs(names, events, doc_start, open_end, max_rank)),
    "rank1": lambda names, events, doc_start, open_end=False, max_rank=1: pairs(names, events, doc_start, open_end, 1),
}
