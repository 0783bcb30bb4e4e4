import random

import pytest

from tests.helpers import random_path
from treegrammar.operators.index import _show
from treegrammar.queries import AUTOMATA
from treegrammar.xpath.automaton import AutomatonLimitError, compile_path, transition
from treegrammar.xpath.parse import UnsupportedPathError, parse_path


@pytest.mark.parametrize(("path", "states"), list(AUTOMATA.items()))
def test_automaton_sizes(path, states):
    assert compile_path(path).n_states == states


@pytest.mark.parametrize("path", ["a", "", "/a[b]", "/a/ancestor::b", "/a/..", "/a/@x='v'", "//following-sibling::a", "/a/text()/b", "/a/count(b)"])
def test_unsupported_paths(path):
    with pytest.raises(UnsupportedPathError):
        parse_path(path)


def test_state_limit():
    with pytest.raises(AutomatonLimitError):
        compile_path("//a/*/*/*/*/*/*/*/*/b", max_states=100)


def test_paths_without_wildcards_have_few_states():
    rng = random.Random(2)
    for _ in range(300):
        path = random_path(rng)
        steps = parse_path(path)
        if any(s.name is None for s in steps) or "following" in path:
            continue
        a = compile_path(path)
        assert a.n_states <= 2 * len(steps)
        assert a.n_states == compile_path(path, minimise=False).n_states  # minimal as built


def test_pruning_and_minimising_change_no_language():
    rng = random.Random(3)
    for _ in range(60):
        path = random_path(rng)
        a, b = compile_path(path), compile_path(path, prune=False, minimise=False)
        for _ in range(30):
            p, q = a.initial, b.initial
            for _ in range(12):
                c = rng.randrange(len(a.classes))
                assert a.selects[p, c] == b.selects[q, c]
                p, q = (a.to_down[p, c], b.to_down[q, c]) if rng.random() < 0.5 else (a.to_right[p, c], b.to_right[q, c])


def test_relevance():
    a = compile_path("/b")
    basic, fine = a.relevance(False)[0], a.relevance(True)[0]
    b = a.classes.index((0, "b"))
    assert basic[a.initial].all()
    assert fine[a.initial].tolist() == [k == b for k in range(len(a.classes))]
    assert not basic[a.universal].any()


def test_paths_are_shown_as_they_were_read():
    for path in ("/a/b//c", "//a/following-sibling::b/*", "/a/text()", "//@x", "/a/@*", "/a//@y"):
        assert "".join(_show(s) for s in parse_path(path)) == path


def test_lazy_transition_agrees_with_tables():
    a = compile_path("//a/b", minimise=False)
    for k, (kind, name) in enumerate(a.classes):
        hits = tuple(s.matches(kind, name or "\0other") for s in a.steps)
        assert transition(a.steps, (0,), hits)[0] == a.selects[a.initial, k]


def test_simple_paths_match_like_a_string_search_along_first_children():
    """Reading labels down a chain of first children, //a1/../an selects exactly where the last n labels are a1..an."""
    rng = random.Random(6)
    for _ in range(60):
        word = [rng.choice("ab") for _ in range(rng.randint(1, 5))]
        a = compile_path("//" + "/".join(word))
        chain = [rng.choice("abc") for _ in range(40)]
        q = a.initial
        for k, label in enumerate(chain):
            c = int(a.classify([(0, label)])[0])
            assert a.selects[q, c] == (chain[max(0, k + 1 - len(word)) : k + 1] == word)
            q = a.to_down[q, c]
