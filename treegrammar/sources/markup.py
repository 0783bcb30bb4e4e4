"""Markup to structure trees: a strict reader for generated XML and a tolerant one for web pages.

Both produce the parenthesis stream of the structure tree: texts become ``_T`` leaves, the attributes of an element
become one ``_A`` child with a child ``@name`` for each and an ``_AT`` leaf below it, and the values go to a list apart.
"""

from __future__ import annotations

import html
import re

import numpy as np

ELEMENT, TEXT, ATTRS, VALUE, ATTR = range(5)
CLOSE = -1

_STRICT = re.compile(r"<(/?)([^\s/>!?][^\s/>]*)([^>]*?)(/?)>|<![^>]*>|<\?[^>]*>|([^<]+)")
_ATTRIBUTE = re.compile(r"([^\s=/]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))")
_LOOSE = re.compile(
    r"<!--.*?(?:-->|\Z)|<(script|style)\b([^>]*)>(.*?)(?:</\1\s*>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:\"[^\"]*\"|'[^']*'|[^>\"'])*)>|<[!?][^>]*>|([^<]+|<)", re.S | re.I
)
#: Fixed values of the tolerant policy: elements without content; start tags that close an open element of the same
#: label, and the containers that stop the search for it.
VOID = frozenset(("br", "meta", "link", "img", "hr", "input"))
SELF_CLOSING, CONTAINERS = frozenset(("p", "li")), frozenset(("body", "article", "nav", "ul", "div"))


class Forest:
    """Documents of one shard as parenthesis streams over a common label table."""

    def __init__(self) -> None:
        self.labels: dict[tuple[int, str], int] = {}
        self.names: list[tuple[int, str]] = []
        self.events: list[int] = []
        self.texts: list[str] = []
        self.doc_ids: list[int] = []
        self.doc_events: list[int] = []
        self.doc_texts: list[int] = []

    def label(self, kind: int, name: str) -> int:
        key = (kind, name)
        got = self.labels.get(key)
        if got is None:
            got = self.labels[key] = len(self.names)
            self.names.append(key)
        return got

    def begin(self, doc_id: int) -> None:
        self.doc_ids.append(doc_id)
        self.doc_events.append(len(self.events))
        self.doc_texts.append(len(self.texts))

    def text(self, value: str) -> None:
        self.events += (self.label(TEXT, "_T"), CLOSE)
        self.texts.append(value)

    def open(self, name: str, attrs: str = "") -> None:
        self.events.append(self.label(ELEMENT, name))
        if "=" in attrs:
            found = [(m[1], html.unescape(next((g for g in m.groups()[1:] if g is not None), ""))) for m in _ATTRIBUTE.finditer(attrs)]
            if found:
                self.events.append(self.label(ATTRS, "_A"))
                for k, v in found:
                    self.events += (self.label(ATTR, "@" + k), self.label(VALUE, "_AT"), CLOSE, CLOSE)
                    self.texts.append(v)
                self.events.append(CLOSE)

    def close(self) -> None:
        self.events.append(CLOSE)

    def add_strict(self, doc_id: int, content: str | None) -> None:
        """A well-formed document or forest; an end tag that does not fit is an error."""
        self.begin(doc_id)
        stack: list[str] = []
        for m in _STRICT.finditer(content or ""):
            end, name, attrs, empty, text = m.groups()
            if text is not None:
                if not text.isspace():
                    self.text(html.unescape(text) if "&" in text else text)
            elif name is not None:
                if end:
                    if not stack or stack.pop() != name:
                        raise ValueError(f"end tag {name} does not fit in document {doc_id}")
                    self.events.append(CLOSE)
                else:
                    self.open(name, attrs)
                    if empty:
                        self.events.append(CLOSE)
                    else:
                        stack.append(name)
        if stack:
            raise ValueError(f"{stack[-1]} is not closed in document {doc_id}")

    def add_loose(self, doc_id: int, content: str | None) -> None:
        """A web page: void and unclosed elements, stray end tags and an early end are all put right."""
        self.begin(doc_id)
        stack: list[str] = []
        for m in _LOOSE.finditer(content or ""):
            if m[1] is not None:
                self.open(m[1].lower(), m[2])
                if m[3] and not m[3].isspace():
                    self.text(m[3])
                self.close()
            elif m[7] is not None:
                if not m[7].isspace():
                    self.text(html.unescape(m[7]))
            elif m[5] is not None:
                name = m[5].lower()
                if m[4]:
                    if name in stack:
                        while True:
                            self.close()
                            if stack.pop() == name:
                                break
                    continue
                if name in SELF_CLOSING:
                    for at in range(len(stack) - 1, -1, -1):
                        if stack[at] == name:
                            for _ in range(len(stack) - at):
                                self.close()
                            del stack[at:]
                            break
                        if stack[at] in CONTAINERS:
                            break
                self.open(name, m[6])
                if name in VOID or m[6].rstrip().endswith("/"):
                    self.close()
                else:
                    stack.append(name)
        for _ in stack:
            self.close()

    def arrays(self) -> tuple[np.ndarray, np.ndarray]:
        """The stream of all documents and the start of each, with the end as last entry."""
        return np.array(self.events, np.int32), np.array([*self.doc_events, len(self.events)], np.int64)


def forest_of(rows: list[tuple[int, str | None]], policy: str = "strict") -> Forest:
    out = Forest()
    add = out.add_loose if policy == "html" else out.add_strict
    for doc_id, content in rows:
        add(doc_id, content)
    return out


def node_table(events: np.ndarray, kinds: list[int]) -> dict[str, np.ndarray]:
    """Per structure node of one document: label, kind, size (structure nodes), parent, level (elements above), element
    pre number (-1 for other kinds), element size, and text number (-1 unless it is a text or value leaf)."""
    is_open = events >= 0
    at = np.flatnonzero(is_open)
    n = len(at)
    depth = np.cumsum(np.where(is_open, 1, -1))
    level = depth[at]
    label = events[at].astype(np.int64)
    kind = np.array(kinds, np.int8)[label] if n else np.empty(0, np.int8)
    # A node ends before the next node that is no deeper.
    order = np.lexsort((np.arange(len(events)), np.where(is_open, depth, depth + 1)))
    opens, closes = order[is_open[order]], order[~is_open[order]]
    end = np.empty(len(events), np.int64)
    end[opens] = closes
    seen = np.cumsum(is_open)
    size = seen[end[at]] - seen[at] + 1
    parent = np.full(n, -1, np.int64)
    last: list[int] = []
    for k, d in enumerate(level.tolist()):
        del last[d - 1 :]
        if last:
            parent[k] = last[-1]
        last.append(k)
    element = kind == ELEMENT
    before = np.cumsum(element) - element
    pre = np.where(element, before, -1)
    esize = np.where(element, np.append(np.cumsum(element), 0)[np.arange(n) + size - 1] - before, 0)
    elevel = np.zeros(n, np.int64)
    up = parent >= 0
    for d in range(2, int(level.max(initial=0)) + 1):
        m = (level == d) & up
        elevel[m] = elevel[parent[m]] + element[parent[m]]
    leaf = (kind == TEXT) | (kind == VALUE)
    text_no = np.where(leaf, np.cumsum(leaf) - 1, -1)
    return {"label": label, "kind": kind, "size": size, "parent": parent, "level": elevel, "pre": pre, "element_size": esize, "text_no": text_no}
