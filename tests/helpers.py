"""Random documents and a brute-force evaluator."""

from __future__ import annotations

import random

import numpy as np

from treegrammar.sources.markup import Forest, forest_of, node_table
from treegrammar.xpath.parse import Step


def random_document(rng: random.Random, size: int) -> str:
    out, stack = "", []
    for _ in range(size):
        r = rng.random()
        if r < 0.5 or not stack:
            tag = rng.choice("abc")
            out += f"<{tag}" + (' k="v&lt;"' if rng.random() < 0.2 else "") + ">"
            stack.append(tag)
        elif r < 0.6:
            out += rng.choice("xyz") + "&amp;"
        else:
            out += f"</{stack.pop()}>"
    return out + "".join(f"</{t}>" for t in reversed(stack))


def random_path(rng: random.Random) -> str:
    p = ""
    for i in range(rng.randint(1, 4)):
        r = rng.random()
        if i and r < 0.25:
            p += "/following-sibling::"
        else:
            p += "//" if r < 0.6 else "/"
        p += rng.choice(["a", "b", "c", "*", "zz"])
    if rng.random() < 0.2:
        p += rng.choice(["/text()", "//text()", "/@k", "//@*"])
    return p


def forest(rng: random.Random, docs: int, size: int) -> Forest:
    return forest_of([(i, random_document(rng, rng.randint(0, size))) for i in range(docs)])


def document(f: Forest, d: int) -> np.ndarray:
    return np.array(f.events[f.doc_events[d] : [*f.doc_events, len(f.events)][d + 1]], np.int32)


def brute_force(f: Forest, d: int, steps: list[Step]) -> tuple[list[int], dict]:
    """Numbers of the selected structure nodes of a document, and its node table."""
    t = node_table(document(f, d), [k for k, _ in f.names])
    parent, labels = t["parent"].tolist(), [f.names[x] for x in t["label"].tolist()]
    now = {-1}
    for s in steps:
        new = set()
        for v, lab in enumerate(labels):
            if not s.matches(*lab):
                continue
            if s.axis == "child":
                ok = parent[v] in now
            elif s.axis == "descendant":
                a = parent[v]
                while a not in now and a >= 0:
                    a = parent[a]
                ok = a in now
            else:
                ok = any(u in now and u < v and parent[u] == parent[v] for u in range(v))
            if ok:
                new.add(v)
        now = new
    return sorted(now), t
