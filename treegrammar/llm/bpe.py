"""BPE encoding and decoding by a prefix-sharing trie.

The distinct words of a batch go into a trie in sorted order. A depth-first walk keeps, for every prefix, the last token
of its encoding: the unique token that ends there and stays apart from the last token of the prefix before it. Words
with a common prefix share that work, and a word's encoding is read back through the last-token chain. Encodings are
kept in a cache of the Python worker that is bounded by its bytes, so frequent words are encoded once.

Words are cut as the tokenizer file says (byte-level pre-tokenization without a prefix space); the strings of added
tokens are matched first and get their own ids. Decoding joins the bytes of the ids and replaces invalid UTF-8.

Defined results: a null text counts as empty and has no ids; texts of any length are cut in one pass, never shortened;
repeated rows count each; extra columns are ignored by ``encode`` and kept by ``with_tokens``; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterable, Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes of words and encodings, about, pairs of tokens whose border a worker keeps, and steps between states; beyond that a cache starts anew,
#: the first with the words of the texts at hand. They take some 150 MB at most.
CACHE_BYTES, CACHE_PAIRS, CACHE_STEPS, WORD_BYTES = 80 << 20, 300_000, 300_000, 190
#: The byte-level pre-tokenization pattern; white space as Unicode defines it.
_SPACE = r"\p{White_Space}"
PATTERN = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{_SPACE}\p{{L}}\p{{N}}]+|{_SPACE}+(?!\P{{White_Space}})|{_SPACE}+"

#: The same pattern where a text is ASCII only; the plain engine is faster.
PATTERN_ASCII = r"'s|'t|'re|'ve|'m|'ll|'d| ?[A-Za-z]+| ?[0-9]+| ?[^\t-\r A-Za-z0-9]+|[\t-\r ]+(?![^\t-\r ])|[\t-\r ]+"


def byte_alphabet() -> dict[str, int]:
    """The printable character that stands for each byte in byte-level vocabularies, and its byte."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(0x100 + k): b for k, b in enumerate(rest)}


class Bpe:
    """Vocabulary, merge ranks and the encoder state of one tokenizer file."""

    def __init__(self, text: str):
        spec = json.loads(text)
        model, pre = spec["model"], spec["pre_tokenizer"]
        if model["type"] != "BPE" or pre["type"] != "ByteLevel" or pre["add_prefix_space"] or spec["normalizer"]:
            raise ValueError("only byte-level BPE without normalizer and prefix space is read")
        alphabet = byte_alphabet()
        raw = lambda s: bytes(alphabet[c] for c in s)
        self.ids = {raw(t): i for t, i in model["vocab"].items()}
        self.token = {i: t for t, i in self.ids.items()}
        self.rank: dict[tuple[int, int], int] = {}
        self.parts: dict[int, tuple[int, int, int]] = {}
        for k, m in enumerate(model["merges"]):
            x, y = (raw(s) for s in (m.split(" ") if isinstance(m, str) else m))
            a, b, c = self.ids[x], self.ids[y], self.ids[x + y]
            self.rank.setdefault((a, b), k)
            self.parts.setdefault(c, (k, a, b))
        # Suffix automaton, made as far as texts go: a state is the longest end of the bytes read that begins a token.
        self.begins = {t[:k] for t in self.ids for k in range(1, len(t) + 1)}
        self.states: dict[bytes, int] = {}
        self.shown: list[bytes] = []  # the bytes of each state
        self.ends: list[tuple[tuple[int, int], ...]] = []  # tokens that end in a state and their lengths, the longest first
        self.goto: dict[int, int] = {}  # state << 8 | byte -> state
        self._state(b"")
        self.edges: tuple[dict, dict] = ({}, {})
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.token |= {i: s.encode() for s, i in self.added.items()}
        self.cut, self.cut_ascii = regex.compile(PATTERN), re.compile(PATTERN_ASCII)
        self.special = regex.compile("|".join(regex.escape(s) for s in sorted(self.added, key=len, reverse=True))) if self.added else None
        self.apart: dict[int, bool] = {}
        self.known: dict[str, str] = {}  # a word's ids, joined by commas
        self.held = 0  # bytes of the words known, about
        self.named = {str(i): t for i, t in self.token.items()}

    def _edges(self, token: int, right: bool) -> list[tuple[int, int, float]]:
        """Pieces on one edge of a token while it grows: the piece, and the ranks at which it is made and absorbed."""
        known = self.edges[right]
        if token not in known:
            out, absorbed, piece = [], float("inf"), token
            while True:
                made = self.parts.get(piece)
                out.append((piece, made[0] if made else -1, absorbed))
                if not made:
                    break
                absorbed, piece = made[0], made[2 if right else 1]
            known[token] = out
        return known[token]

    def stay_apart(self, a: int, b: int) -> bool:
        """Whether no merge ever crosses the border between the tokens a and b when their bytes stand side by side."""
        got, left, rank = True, self._edges(a, True), self.rank.get
        for y, made_y, gone_y in self._edges(b, False):
            for x, made_x, gone_x in left:
                m = rank((x, y))
                # Equal ranks merge from the left, so a piece absorbed to its left goes first, one absorbed to its right does not.
                if m is not None and made_x < m and made_y < m and m < gone_x and m <= gone_y:
                    got = False
                    break
            if not got:
                break
        if len(self.apart) > CACHE_PAIRS:
            self.apart.clear()
        self.apart[a << 32 | b] = got
        return got

    def _state(self, end: bytes) -> int:
        if end not in self.states:
            self.states[end] = len(self.shown)
            self.shown.append(end)
            self.ends.append(tuple((self.ids[end[k:]], len(end) - k) for k in range(len(end)) if end[k:] in self.ids))
        return self.states[end]

    def step(self, state: int, byte: int) -> int:
        """The state after one more byte."""
        end = self.shown[state] + bytes([byte])
        while end and end not in self.begins:
            end = end[1:]
        if len(self.goto) > CACHE_STEPS:
            self.goto.clear()
        got = self.goto[state << 8 | byte] = self._state(end)
        return got

    def encode_words(self, words: Iterable[bytes]) -> Iterator[tuple[bytes, list[int]]]:
        """Each distinct word and its ids, in sorted order; prefixes that words share are worked out once."""
        token, known, apart, goto, step, ends = self.token, self.apart.get, self.stay_apart, self.goto.get, self.step, self.ends
        last: list[int] = [-1]  # last[d]: last token of the encoding of the first d bytes on the current path
        path: list[int] = [0]  # path[d]: the state after them
        before = b""
        for word in sorted(words):
            d, top = 0, min(len(before), len(word))
            while d < top and before[d] == word[d]:
                d += 1
            del last[d + 1 :], path[d + 1 :]
            state = path[d]
            for end in range(d + 1, len(word) + 1):
                byte = word[end - 1]
                new = goto(state << 8 | byte)
                state = step(state, byte) if new is None else new
                path.append(state)
                for t, size in ends[state]:
                    if size == end:
                        last.append(t)
                        break
                    left = last[end - size]
                    ok = known(left << 32 | t)
                    if apart(left, t) if ok is None else ok:
                        last.append(t)
                        break
                else:
                    raise ValueError("the vocabulary lacks a byte")
            before, out, at = word, [], len(word)
            while at:
                out.append(last[at])
                at -= len(token[last[at]])
            yield word, out[::-1]

    def learn(self, words: set[str]) -> None:
        """Add the encodings of words that are not known yet."""
        if self.held > CACHE_BYTES:
            kept = {w: self.known[w] for w in words if w in self.known}
            self.known, self.held = kept, sum(WORD_BYTES + len(w) + len(i) for w, i in kept.items())
        new = {w.encode("utf-8", "surrogatepass"): w for w in words if w not in self.known}
        for raw, ids in self.encode_words(new):
            shown = ",".join(map(str, ids))
            self.known[new[raw]] = shown
            self.held += WORD_BYTES + len(raw) + len(shown)

    def pieces(self, text: str) -> list[str | int]:
        """The text cut at added tokens, which become their ids."""
        if self.special is None or not any(s in text for s in self.added):
            return [text]
        out, at = [], 0
        for m in self.special.finditer(text):
            out += [text[at : m.start()], self.added[m.group()]]
            at = m.end()
        return [*out, text[at:]]

    def encode_texts(self, texts: list[str]) -> Iterator[tuple[str, int, bytes]]:
        """For each text its ids joined by commas, their number, and the bytes they decode to."""
        wide, plain = self.cut.findall, self.cut_ascii.findall
        cuts = [[x if isinstance(x, int) else plain(x) if x.isascii() else wide(x) for x in self.pieces(t)] for t in texts]
        self.learn(set().union(*(x for c in cuts for x in c if not isinstance(x, int))))
        known, named = self.known.__getitem__, self.named.__getitem__
        for c in cuts:
            ids = ",".join([str(x) if isinstance(x, int) else ",".join(map(known, x)) for x in c if x != []])
            each = ids.split(",") if ids else []
            yield ids, len(each), b"".join(map(named, each))

    def decode(self, ids: Iterable[int]) -> str:
        return b"".join([self.token[i] for i in ids]).decode("utf-8", "replace")


_LOADED: dict[str, Bpe] = {}


def loaded(text: str) -> Bpe:
    """One encoder a worker for each tokenizer file, so that its bounded cache outlives a task."""
    key = hashlib.sha256(text.encode()).hexdigest()
    if key not in _LOADED:
        _LOADED.clear()
        _LOADED[key] = Bpe(text)
    return _LOADED[key]


def read_tokenizer(path: str) -> str:
    with open(path, encoding="utf-8") as f:
        return f.read()


def digests(docs: DataFrame, tokenizer: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every row; tokenizer: the text of a tokenizer file, a few MB."""
    shared = docs.sparkSession.sparkContext.broadcast(tokenizer)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = loaded(shared.value)
        for batch in batches:
            for at in range(0, batch.num_rows, 128):
                part = batch.slice(at, 128)
                got = list(bpe.encode_texts([t or "" for t in part.column(1).to_pylist()]))
                cols = [part.column(0), pa.array([g[1] for g in got], pa.int64()), pa.array([hashlib.sha256(g[0].encode()).hexdigest() for g in got]), pa.array([hashlib.sha256(g[2].decode("utf-8", "replace").encode()).hexdigest() for g in got])]
                yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode(docs: DataFrame, tokenizer: str) -> DataFrame:
    """doc_id and the token ids of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(tokenizer)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = loaded(shared.value)
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                part = batch.slice(at, 64)
                ids = [[int(x) for x in g[0].split(",") if x] for g in bpe.encode_texts([t or "" for t in part.column(1).to_pylist()])]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ids, pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, ids array<int>")


def decode(encoded: DataFrame, tokenizer: str) -> DataFrame:
    """doc_id and the text of the ids of every row (doc_id, ids)."""
    shared = encoded.sparkSession.sparkContext.broadcast(tokenizer)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = loaded(shared.value)
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                part = batch.slice(at, 64)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([bpe.decode(ids or []) for ids in part.column(1).to_pylist()], pa.string())], names=["doc_id", "text"])

    return encoded.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("ids").cast(T.ArrayType(T.IntegerType())).alias("ids")).mapInArrow(run, "doc_id long, text string")
