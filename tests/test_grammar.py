import random

import numpy as np
import pytest

from tests.helpers import forest
from treegrammar.grammar import compress
from treegrammar.grammar.model import Grammar, GrammarLimitError, pack, unpack
from treegrammar.grammar.normal_form import general, inline_single, normal_form
from treegrammar.operators.index import start_parentheses
from treegrammar.queries import WORKED
from treegrammar.sources.markup import forest_of
from treegrammar.texts import TextBuffer


def same_trees(g: Grammar, events, doc_start) -> None:
    stream, at = g.expand(), 0
    for d, n in enumerate(g.totals("node").tolist()):
        own = stream[at : at + 2 * n + 1]
        at += 2 * n + 1
        assert own[-1] == (-2 if g.open_end and d == len(doc_start) - 2 else -1)
        assert own[:-1].tolist() == events[doc_start[d] : doc_start[d + 1]].tolist()
    assert at == len(stream)


@pytest.mark.parametrize("name", list(compress.COMPRESSORS))
@pytest.mark.parametrize("open_end", [False, True])
def test_round_trip(name, open_end):
    rng = random.Random(len(name) + open_end)
    for _ in range(25):
        f = forest(rng, rng.randint(1, 4), 60)
        ev, ds = f.arrays()
        g = compress.COMPRESSORS[name](f.names, ev, ds, open_end)
        same_trees(g, ev, ds)
        outer, hole, inner, rank = unpack(pack(g), g.n_labels)
        assert (outer == g.outer).all() and (hole == g.hole).all() and (inner == g.inner).all() and (rank == g.rank).all()


def test_pruning_and_rank_one_keep_the_trees():
    rng = random.Random(5)
    for _ in range(30):
        f = forest(rng, 2, 80)
        ev, ds = f.arrays()
        same_trees(compress.pairs(f.names, ev, ds, prune=True), ev, ds)
        g = compress.rank_one(compress.pairs(f.names, ev, ds, max_rank=8))
        assert g.rank[g.first_rule :].max(initial=0) <= 1
        same_trees(g, ev, ds)


@pytest.mark.parametrize("content", ["", "<a/>", "<a>x</a>", '<a k="1"/>', "<a/><b/>", "<a>" * 3000 + "</a>" * 3000, "<r>" + "<a/>" * 100_000 + "</r>"])
def test_edge_documents(content):
    f = forest_of([(1, content)])
    ev, ds = f.arrays()
    g = compress.pairs(f.names, ev, ds)
    same_trees(g, ev, ds)
    if content.startswith("<r>"):
        assert g.edges() < 200  # a list of equal siblings costs logarithmically many rules


def test_rank_limit():
    f = forest_of([(1, "<a/>")])
    ev, ds = f.arrays()
    g = compress.one_rule(f.names, ev, ds)
    for rank, ok in ((15, True), (16, False)):
        h = Grammar(g.names, np.array([0]), np.array([1]), np.array([0]), np.append(g.rank, rank), g.start, g.doc_start)
        if ok:
            pack(h)
        else:
            with pytest.raises(GrammarLimitError):
                pack(h)


def test_worked_terms():
    """The two worked trees: eleven nodes; shared subtrees save edges, and all grammars give the tree back."""
    f = forest_of([(0, WORKED[0])])
    ev, ds = f.arrays()
    plain, shared, small = (compress.COMPRESSORS[c](f.names, ev, ds) for c in ("one_rule", "dag", "pairs"))
    assert plain.totals("node").tolist() == [11]
    for g in (plain, shared, small):
        same_trees(g, ev, ds)
    assert shared.edges() < plain.edges() and small.edges() <= shared.edges()


def test_tables_agree_with_expansion():
    rng = random.Random(11)
    for _ in range(30):
        f = forest(rng, 3, 60)
        ev, ds = f.arrays()
        g = compress.pairs(f.names, ev, ds)
        assert g.totals("node").sum() * 2 == len(ev)
        assert g.totals("text").sum() == len(f.texts)
        ends = g.start_ends()
        assert all(ends[b] == e for b, e in zip(g.doc_start[:-1].tolist(), g.doc_start[1:].tolist(), strict=True))
        skip = g.start_skips("elem")
        assert [int(skip[b]) for b in g.doc_start[:-1]] == g.totals("elem").tolist()
        bp = start_parentheses(g)
        assert bp.sum() * 2 == len(bp) == 2 * len(g.start)
        depth = np.cumsum(np.where(bp, 1, -1))
        assert depth.min(initial=0) >= 0 and (len(depth) == 0 or depth[-1] == 0)
        labels = {s: {s} for s in range(g.n_labels)} | {g.null: set(), g.end: set()}
        for k in range(g.n_rules):
            labels[g.first_rule + k] = labels[int(g.outer[k])] | labels[int(g.inner[k])]
            mask = {b for b in range(g.n_labels) if int(g.masks()[g.first_rule + k, b >> 6]) >> (b & 63) & 1}
            assert mask == labels[g.first_rule + k]


def test_pairs_beat_shared_subtrees_on_records():
    rows = [(i, "<log>" + f"<day><click><value>{i}</value><props><k>v</k></props></click><view/></day>" * 30 + "</log>") for i in range(20)]
    f = forest_of(rows)
    ev, ds = f.arrays()
    edges = {c: compress.COMPRESSORS[c](f.names, ev, ds).edges() for c in ("pairs", "dag", "one_rule")}
    assert edges["pairs"] <= edges["dag"] < edges["one_rule"] / 5


def test_normal_form_bounds():
    """The normal form generates the same trees; its size grows by the rank at most, and rules are at most twice the size."""
    rng = random.Random(21)
    for k in range(40):
        f = forest(rng, rng.randint(1, 3), 120)
        ev, ds = f.arrays()
        g = compress.pairs(f.names, ev, ds, k % 3 == 0, max_rank=rng.choice([1, 2, 3, 8]))
        big = inline_single(general(g))
        h = normal_form(big)
        same_trees(h, ev, ds)
        r = max((big.rank[v] for v in big.rules), default=0)
        assert h.n_rules <= 2 * max(1, big.edges()) and h.edges() <= (1 + r) * max(1, big.edges()) + len(big.rules)
        assert h.rank[h.first_rule :].max(initial=0) <= max(2, r + 2)
        assert len(big.rules) <= g.n_rules and big.edges() <= g.edges()
        same = normal_form(general(g))
        same_trees(same, ev, ds)


def test_text_buffer():
    t = TextBuffer(["", "a", "äö", "x" * 500])
    assert [t[i] for i in range(4)] == ["", "a", "äö", "x" * 500] and len(t) == 4 and t.bytes() > 500
    with pytest.raises(IndexError):
        t[4]


def test_triples_follow_their_tree():
    """Kept from round to round, the triples are those of a tree looked at anew; chains of one label included."""
    rng = random.Random(8)
    for k in range(30):
        f = forest_of([(0, "<a>" * 60 + "</a>" * 60)]) if k == 0 else forest(rng, rng.randint(1, 3), 150)
        tree = compress.Tree(f.names, *f.arrays(), k % 3 == 0, 1 + k % 3)
        triples = compress.Triples(tree)
        for _ in range(12):
            most = triples.most(4)
            if not most:
                break
            nodes = triples.nodes([n for _, _, n in most])
            assert [len(x) for x in nodes] == [c for c, _, _ in most]
            x, i, y = most[0][1] >> 33, most[0][1] >> 29 & 15, most[0][1] & (1 << 29) - 1
            v = tree.alternate(nodes[0]) if x == y else nodes[0]
            above = tree.parent[v]
            tree.contract(v, x, i, y)
            triples.update(np.concatenate([v, tree.around(above)]))
            v, key = tree.edges()
            got = triples.of >= 0
            assert np.array_equal(np.flatnonzero(got), v) and np.array_equal(triples.key[triples.of[got]], key)
            assert np.array_equal(triples.count, np.bincount(triples.of[got], minlength=len(triples.key)))


def test_rounds_look_at_changed_edges_and_contract_together(monkeypatch):
    """Pattern search finds the edges of the whole tree once, and folding the start contracts edges of many triples in a step."""
    from treegrammar.grammar.compress import Tree

    rng, whole, steps = random.Random(11), [], []
    f = forest(rng, 4, 2000)
    ev, ds = f.arrays()
    edges, splice = Tree.edges, Tree.splice
    monkeypatch.setattr(Tree, "edges", lambda self: whole.append(1) or edges(self))
    g = compress.patterns(f.names, ev, ds)
    same_trees(g, ev, ds)
    assert g.n_rules > 10 and len(whole) == 1
    monkeypatch.setattr(Tree, "splice", lambda self, *a: steps.append(1) or splice(self, *a))
    one = compress.one_rule(f.names, ev, ds)
    g = compress.no_start_rule(one)
    same_trees(g, ev, ds)
    assert g.n_rules > 5 * len(steps) > 0
