import random

import numpy as np
import pytest

from tests.helpers import brute_force, document, forest, random_path
from treegrammar.baselines.trees import PointerTree, SuccinctTree, traverse
from treegrammar.grammar import compress
from treegrammar.sources.markup import forest_of
from treegrammar.views import generic
from treegrammar.views.chunkwise import Chunkwise, render, subtree_ends
from treegrammar.views.nodewise import Cursor
from treegrammar.views.rulewise import Run
from treegrammar.xpath.automaton import compile_path

D1 = "<g>w0<f><f><a><b>w1</b></a><c>w2</c></f><a><c>w3</c></a><c>w4</c></f><a><c>w5</c></a><c>w6</c></g>"


def cases(seed: int, n: int, size: int = 50):
    rng = random.Random(seed)
    names = list(compress.COMPRESSORS)
    for k in range(n):
        f = forest(rng, rng.randint(1, 3), size)
        ev, ds = f.arrays()
        name, open_end, path = names[k % len(names)], k % 4 == 0, random_path(rng)
        g = compress.COMPRESSORS[name](f.names, ev, ds, open_end)
        a = compile_path(path)
        yield f, g, a, path, [brute_force(f, d, a.steps) for d in range(len(f.doc_ids))]


def test_counts_agree_with_brute_force_under_all_options():
    for _, g, a, path, want in cases(1, 160):
        n = [len(w[0]) for w in want]
        exits = set()
        visits = {}
        for tag, options in {"none": {"jump": False}, "basic": {"fine": False}, "fine": {}, "noskip": {"skip": False}}.items():
            r = Run(g, a, **options)
            got, last = r.lazy_count()
            assert got.tolist() == n, (path, tag)
            exits.add(last)
            visits[tag] = r.count.visited
            # One evaluation for each symbol and state at most.
            assert r.count.visited <= (g.first_rule + g.n_rules) * a.n_states
            got, last = r.eager_count()
            assert got.tolist() == n
            exits.add(last)
        assert visits["fine"] <= visits["basic"] <= visits["none"]
        assert not g.open_end or len(exits) == 1


def test_materialize_agrees_with_brute_force():
    for _, g, a, path, want in cases(2, 120):
        for options in ({}, {"start_skip": False}):
            got, _ = Chunkwise(Run(g, a), **options).materialize()
            for pos, (nodes, t) in zip(got, want, strict=True):
                assert pos[1].tolist() == nodes, path
                elements = t["pre"][nodes] >= 0
                assert pos[0][elements].tolist() == t["pre"][nodes][elements].tolist()
        few, _ = Chunkwise(Run(g, a)).materialize(limit=1)
        assert few[0].shape[1] == min(1, len(want[0][0]))


def test_serialize_agrees_with_the_source():
    for f, g, a, path, want in cases(3, 120):
        for copy in (True, False):
            got, _ = Chunkwise(Run(g, a), copy).serialize(f.texts, f.doc_texts)
            for d, (tags, res) in enumerate(got):
                ev, t = document(f, d), want[d][1]
                texts_before = np.cumsum(np.isin(t["kind"], [1, 3]))
                opens = np.flatnonzero(ev >= 0)
                ends = subtree_ends(tags, res[0]).tolist() if res.shape[1] else []
                mine = [render(tags[b:e].tolist(), f.names, f.texts, f.doc_texts[d] + x) for b, e, x in zip(res[0].tolist(), ends, res[3].tolist(), strict=True)]
                source = []
                for v in want[d][0]:
                    b = opens[v]
                    e = subtree_ends(ev, np.array([b]))[0]
                    source.append(render(ev[b:e].tolist(), f.names, f.texts, f.doc_texts[d] + (int(texts_before[v - 1]) if v else 0)))
                assert mine == source, path


def test_node_wise_view():
    for f, g, a, path, want in cases(4, 60, 35):
        for pool in (True, False):
            c = Cursor(g, pool)
            for d, root in enumerate(c.roots()):
                ev, t = document(f, d), want[d][1]
                for tagged in (True, False):
                    assert generic.count(c, root, path, tagged) == len(want[d][0]), path
                runs = [c.traverse(root, o, m) for o in ("dflr", "dfrl") for m in ("rec", "iter")]
                assert runs[0] == runs[1] and runs[2] == runs[3] and runs[0][0] == len(t["label"])
                if len(ev):
                    for tree in (PointerTree(ev, f.names), SuccinctTree(ev, f.names)):
                        assert [traverse(tree, 0, o, m) for o in ("dflr", "dfrl") for m in ("rec", "iter")] == runs
                elements = np.flatnonzero(t["pre"] >= 0)
                for p, v in enumerate(elements.tolist()):
                    assert c.label(c.locate(d, p)) == t["label"][v]
                assert c.locate(d, len(elements)) is None


def test_tagged_jumps():
    rng = random.Random(8)
    for _ in range(40):
        f = forest(rng, 1, 50)
        ev, ds = f.arrays()
        g = compress.pairs(f.names, ev, ds)
        c, (_, t) = Cursor(g), brute_force(f, 0, compile_path("//*").steps)
        elements = np.flatnonzero(t["pre"] >= 0).tolist()
        for p, v in enumerate(elements):
            for lab in range(len(f.names)):
                inside = [u for u in range(v + 1, v + int(t["size"][v])) if t["label"][u] == lab]
                after = [u for u in range(v + int(t["size"][v]), len(t["label"])) if t["label"][u] == lab]
                node = c.locate(0, p)
                assert (c.tagged_desc(node, lab) is not None) == bool(inside)
                assert (c.tagged_foll(node, lab) is not None) == bool(after)


@pytest.mark.parametrize(("path", "n"), [("//c", 5), ("//b", 1), ("//f//b", 1), ("//f//c", 3), ("/b", 0), ("//*//*", 11), ("//*//*//*//*", 4)])
def test_worked_document(path, n):
    f = forest_of([(0, D1)])
    ev, ds = f.arrays()
    for name in compress.COMPRESSORS:
        g = compress.COMPRESSORS[name](f.names, ev, ds)
        assert Run(g, compile_path(path)).lazy_count()[0].tolist() == [n]


def test_worked_result_list():
    """The five results start at tags 1, 4, 7, 10 and 13, with texts 2 to 6; stretches met before are copied."""
    f = forest_of([(0, D1)])
    ev, ds = f.arrays()
    g = compress.pairs(f.names, ev, ds)
    (tags, res), = Chunkwise(Run(g, compile_path("//c"))).serialize(f.texts, f.doc_texts)[0]
    assert list(zip((res[0] // 4 * 3 + 1).tolist(), res[3].tolist(), strict=True)) == [(1, 2), (4, 3), (7, 4), (10, 5), (13, 6)]
    assert len(tags) == 20  # open, open text, close text, close, five times
    (tags, res), = Chunkwise(Run(g, compile_path("//b"))).serialize(f.texts, f.doc_texts)[0]
    assert render(tags.tolist(), f.names, f.texts, int(res[3][0])) == "<b>w1</b>"


def test_attributes_and_texts():
    f = forest_of([(0, '<tag k="7" m="8">v</tag>')])
    assert f.texts == ["7", "8", "v"]
    ev, ds = f.arrays()
    g = compress.pairs(f.names, ev, ds)
    assert g.totals("node").tolist() == [7] and g.totals("elem").tolist() == [1]
    for path, n in (("//@*", 2), ("//text()", 1), ("//*", 1), ("/tag/@k", 1), ("//@none", 0)):
        assert Run(g, compile_path(path)).lazy_count()[0].tolist() == [n]


def test_jumping_on_and_off_the_spine():
    """The last hole of a pattern keeps the state only where it lies on the path of second children."""
    for content in ("<r>" + "<f><a><c/><c/></a></f>" * 8 + "<b/></r>", "<r>" + "<f><b/><a><c/><c/></a></f>" * 8 + "</r>", "<f>" * 12 + "<b/>" + "</f>" * 12):
        f = forest_of([(0, content)])
        ev, ds = f.arrays()
        g = compress.pairs(f.names, ev, ds)
        for path in ("/b", "/r/b", "/r/f/b", "//b", "/f/f/f/b"):
            want = len(brute_force(f, 0, compile_path(path).steps)[0])
            assert Run(g, compile_path(path)).lazy_count()[0].tolist() == [want]
            assert Run(g, compile_path(path), jump=False).lazy_count()[0].tolist() == [want]
