"""A plain top-down path evaluator on the node-wise interface, with or without jumps to labels."""

from __future__ import annotations

from treegrammar.views.nodewise import Cursor
from treegrammar.xpath.parse import CHILD, DESCENDANT, Step, parse_path


def select(cursor: Cursor, root, path: str | list[Step], use_tagged: bool = True) -> list:
    """The distinct nodes of a document that a path selects."""
    steps = parse_path(path) if isinstance(path, str) else path
    names = cursor.g.names
    number = {n: k for k, n in enumerate(names)}
    if cursor.label(root) >= len(names):
        return []

    def siblings(node):
        while node is not None:
            yield node
            node = cursor.next_sibling(node)

    def below(node):
        stack = [cursor.first_child(node)]
        while stack:
            n = stack.pop()
            if n is not None:
                yield n
                stack += [cursor.next_sibling(n), cursor.first_child(n)]

    def tagged(node, label: int):
        """Descendants with a label; symbols that do not generate it are jumped."""
        masks, word, bit = cursor.g.masks(), label >> 6, 1 << (label & 63)
        stack = [cursor.at_hole(node, 1)]
        while stack:
            c = stack.pop()
            s = cursor.symbol(c)
            if s == label:
                yield c
            if s >= cursor.f and int(masks[s, word]) & bit:
                stack.append(cursor.outer_part(c, s))
                continue
            stack += [cursor.at_hole(c, k) for k in range(cursor.rank[s], 0, -1)]

    here: list | None = None  # None: the virtual root above all roots
    for step in steps:
        found: dict = {}
        wanted = number.get(({"element": 0, "text": 1, "attrs": 2, "attr": 4}[step.kind], step.name if step.name else {"text": "_T", "attrs": "_A"}.get(step.kind, "")))
        one_label = step.name is not None or step.kind in ("text", "attrs")
        ok = lambda n: step.matches(*names[cursor.label(n)])  # noqa: B023, E731
        if here is None:
            tops = list(siblings(root))
            pool = tops if step.axis == CHILD else (x for t in tops for x in (t, *below(t)))
            found = dict.fromkeys(n for n in pool if ok(n))
        else:
            for n in here:
                if step.axis == CHILD:
                    got = siblings(cursor.first_child(n))
                elif step.axis == DESCENDANT:
                    if use_tagged and one_label:
                        found.update(dict.fromkeys(tagged(n, wanted) if wanted is not None else ()))
                        continue
                    got = below(n)
                else:
                    got = siblings(cursor.next_sibling(n))
                found.update(dict.fromkeys(x for x in got if ok(x)))
        here = list(found)
    return here or []


def count(cursor: Cursor, root, path: str | list[Step], use_tagged: bool = True) -> int:
    return len(select(cursor, root, path, use_tagged))
