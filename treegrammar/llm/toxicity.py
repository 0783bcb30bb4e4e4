"""Toxicity by the nearest labelled examples under exact TF-IDF cosine, found with a block-max inverted index.

Labelled examples (a bounded sample, ``MAX_EXAMPLES`` a class, equal word sequences once) become TF-IDF vectors over all their words: none is
left out and the vocabulary has no cap. The inverse document frequency is taken over all documents; it is multiplied by
the word's chi-square between the two labels, since plain TF-IDF follows the topic of a text instead of its tone.

Examples are put in blocks of ``BLOCK`` similar ones. A word's posting list is cut at the blocks, and each piece has the
largest weight in it, so a query bounds the cosine of every block by the pieces of its words alone. The blocks with the
highest bounds are opened first; then every block whose bound reaches the k-th best cosine found there. The neighbours are exactly those of a
full scan, ties going to the smaller id.

The score is the distance-weighted vote of the k neighbours, put through a monotone calibration that is fitted on the
examples' own leave-one-out votes and weighted back to the true share of labels. Texts that share no word with an example
get the smoothed share of toxic examples among those without words. The nearest examples come along as evidence.

Defined results: null and empty texts hold no word; with no labelled rows every score is 0; examples with a null label
or id are left out; repeated labels of an id count once if they agree and each if they differ; repeated rows are scored alike; extra columns are ignored;
texts are read whole. Labels, lang, source and doc_id are never inputs of a score.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treegrammar.llm.holdout import held_out

#: Characters of an example at most: longer labelled texts are left to others, so the sample has a bounded size.
EXAMPLE_CHARS = 40_000
#: Examples a class at most, neighbours, examples a block, blocks that are opened first.
MAX_EXAMPLES, K, BLOCK, FIRST = 1000, 15, 32, 3
_WORD = re.compile(r"[^\W\d_]+")


def words_of(text: str | None) -> Counter:
    """How often each word occurs, in lower case."""
    return Counter(_WORD.findall((text or "").lower()))


def _ranges(start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """The numbers of all ranges, one range behind the other."""
    total = int(length.sum())
    return np.repeat(start - np.cumsum(length) + length, length) + np.arange(total, dtype=start.dtype)


class Neighbours:
    """Block-max inverted index over labelled TF-IDF vectors.

    df and n: document frequencies of the examples' words over all documents, and how many these are; by default over the examples."""

    def __init__(self, examples: list[tuple[int, str, int]], share: float | None = None, df: dict[str, int] | None = None, n: int = 0, k: int = K):
        self.k = k
        once = {(tuple(_WORD.findall(t.lower())), y): (i, y) for i, t, y in reversed(examples)}
        counts, kept = [Counter(w) for w, _ in once], list(once.values())
        ids, labels = [i for i, _ in kept], np.array([y for _, y in kept], np.float64)
        n1, n0 = int(labels.sum()), int(len(labels) - labels.sum())
        self.share = share if share is not None else (n1 / len(labels) if len(labels) else 0.0)
        by_label = [Counter(), Counter()]
        for c, y in zip(counts, labels, strict=True):
            by_label[int(y)].update(c.keys())
        self.vocab = {w: k for k, w in enumerate(sorted(by_label[0].keys() | by_label[1].keys()))}
        a, b = (np.array([by_label[y][w] for w in self.vocab], np.float64) for y in (1, 0))
        p = (a + b) / max(1, n1 + n0)
        chi = (a / max(1, n1) - b / max(1, n0)) ** 2 / (np.maximum(p * (1 - p), 1e-9) * (1 / max(1, n1) + 1 / max(1, n0)))
        if not n1 or not n0:
            chi = np.ones(len(a))
        seen = a + b if df is None else np.array([df.get(w, 0) for w in self.vocab], np.float64)
        self.term_weight = np.log(1 + max(n, len(kept)) / np.maximum(1, seen)) * (chi + 1e-6)
        vectors = [self.vector(counts=c) for c in counts]
        weight = np.where(labels == 1, self.share / max(n1, 1), (1 - self.share) / max(n0, 1))
        have = [i for i, v in enumerate(vectors) if len(v[0])]
        # Examples that lean on the same word share a block.
        have.sort(key=lambda i: (int(vectors[i][0][np.argmax(vectors[i][1])]), i))
        self.ids, self.labels, self.weight = np.array([ids[i] for i in have], np.int64), labels[have], weight[have]
        self._post([vectors[i] for i in have])
        none = [i for i, v in enumerate(vectors) if not len(v[0])]
        total = weight[none].sum()
        self.empty = float(((weight[none] * labels[none]).sum() * len(labels) + self.share) / (total * len(labels) + 1)) if len(labels) else 0.0
        self.opened = 0
        self._calibrate([vectors[i] for i in have])

    def _post(self, vectors: list[tuple[np.ndarray, np.ndarray]]) -> None:
        """Posting lists in pieces: word -> pieces (block, largest weight, postings) -> postings (example, weight)."""
        term = np.concatenate([v[0] for v in vectors]) if vectors else np.empty(0, np.int64)
        row = np.repeat(np.arange(len(vectors)), [len(v[0]) for v in vectors]) if vectors else np.empty(0, np.int64)
        w = np.concatenate([v[1] for v in vectors]) if vectors else np.empty(0, np.float32)
        order = np.lexsort((row, term))
        term, self.row, self.w = term[order], row[order].astype(np.int32), w[order]
        self.blocks = -(-len(vectors) // BLOCK)
        piece = np.flatnonzero(np.diff(term * max(1, self.blocks) + self.row // BLOCK, prepend=-1))
        self.piece_block = (self.row[piece] // BLOCK).astype(np.int32)
        self.piece_start = piece.astype(np.int32)
        self.piece_size = np.diff(piece, append=len(term)).astype(np.int32)
        self.piece_max = np.maximum.reduceat(self.w, piece) if len(piece) else np.empty(0, np.float32)
        self.of_term = np.searchsorted(term[piece], np.arange(len(self.vocab) + 1)).astype(np.int32)

    def vector(self, text: str | None = None, counts: Counter | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Word numbers in order and unit-length weights."""
        counts = words_of(text) if counts is None else counts
        terms = np.fromiter(map(self.vocab.get, counts, repeat(-1)), np.int64, len(counts))
        n = np.fromiter(counts.values(), np.float64, len(counts))[terms >= 0]
        terms = terms[terms >= 0]
        if not len(terms):
            return terms, np.empty(0, np.float32)
        order = np.argsort(terms)
        terms = terms[order]
        w = (1 + np.log(n[order])) * self.term_weight[terms]
        return terms, (w / math.sqrt(float(w @ w))).astype(np.float32)

    def nearest(self, terms: np.ndarray, w: np.ndarray, but: int = -1) -> tuple[np.ndarray, np.ndarray]:
        """Rows and cosines of the k nearest examples (ties to the smaller id), row ``but`` left out."""
        start = self.of_term[terms]
        many = self.of_term[terms + 1] - start
        piece = _ranges(start, many)
        block, weight = self.piece_block[piece], np.repeat(w, many)
        bound = np.bincount(block, self.piece_max[piece] * weight, self.blocks)
        sims = np.zeros(len(self.ids))
        first = np.argsort(-bound, kind="stable")[:FIRST]
        todo = np.zeros(self.blocks, bool)
        todo[first] = True
        for again in (True, False):
            pick = todo[block]
            size = self.piece_size[piece[pick]]
            at = _ranges(self.piece_start[piece[pick]], size)
            sims += np.bincount(self.row[at], self.w[at] * np.repeat(weight[pick], size), len(sims))
            if but >= 0:
                sims[but] = 0
            self.opened += int(todo.sum())
            if again:
                least = np.partition(sims, -self.k)[-self.k] if len(sims) > self.k else 0.0
                todo = (bound >= least - 1e-5) & (bound > 0) & ~todo
                if not todo.any():
                    break
        if len(sims) > self.k:
            rows = np.flatnonzero(sims >= np.partition(sims, -self.k)[-self.k] - 1e-6)
        else:
            rows = np.arange(len(sims))
        rows = rows[sims[rows] > 0]
        rows = rows[np.lexsort((self.ids[rows], -np.round(sims[rows], 6)))[: self.k]]
        return rows, sims[rows]

    def vote(self, rows: np.ndarray, sims: np.ndarray) -> float:
        if not len(rows):
            return self.empty
        w = self.weight[rows] / (1.05 - np.minimum(sims, 1))
        return float((w * self.labels[rows]).sum() / w.sum())

    def _calibrate(self, vectors: list[tuple[np.ndarray, np.ndarray]]) -> None:
        """Monotone steps from leave-one-out votes to the share of toxic examples (pool adjacent violators)."""
        raw = np.array([self.vote(*self.nearest(t, w, i)) for i, (t, w) in enumerate(vectors)])
        order = np.argsort(raw, kind="stable")
        pools: list[list[float]] = []
        for i in order.tolist():
            pools.append([self.weight[i] * self.labels[i], self.weight[i], raw[i]])
            while len(pools) > 1 and pools[-2][0] * pools[-1][1] >= pools[-1][0] * pools[-2][1]:
                y, w, _ = pools.pop()
                pools[-1][0] += y
                pools[-1][1] += w
        unit = float(self.weight.mean()) if len(self.weight) else 1.0
        self.steps = np.array([p[2] for p in pools])
        self.values = np.array([(p[0] + unit * self.share) / (p[1] + unit) for p in pools])

    def score(self, text: str | None) -> tuple[float, list[int]]:
        """The calibrated score and the ids of the three nearest examples."""
        terms, w = self.vector(text)
        if not len(terms) or not len(self.ids):
            return self.empty, []
        rows, sims = self.nearest(terms, w)
        if not len(rows):
            return self.empty, []
        at = np.searchsorted(self.steps, self.vote(rows, sims) + 1e-12, side="right") - 1
        return float(self.values[max(0, at)]), self.ids[rows[:3]].tolist()


def document_frequencies(spark: SparkSession, docs: DataFrame, vocab: set[str]) -> tuple[dict[str, int], int]:
    """In how many rows of ``docs`` each word of ``vocab`` occurs, and the number of rows; vocab: the words of a bounded sample."""
    shared = spark.sparkContext.broadcast(vocab)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, df, n = shared.value, Counter(), 0
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                for text in batch.column(0).slice(at, 512).to_pylist():
                    df.update(own.intersection(_WORD.findall((text or "").lower())))
                    n += 1
        df[""] = n
        yield pa.RecordBatch.from_arrays([pa.array(list(df), pa.string()), pa.array(list(df.values()), pa.int64())], names=["word", "n"])

    sums = docs.select(F.col("text").cast("string").alias("text")).mapInArrow(run, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    got = {r["word"]: r["n"] for r in sums.toLocalIterator()}
    shared.unpersist()
    return got, got.pop("", 0)


def fit(spark: SparkSession, docs: DataFrame, labels: DataFrame, max_examples: int = MAX_EXAMPLES) -> Neighbours:
    """An index of labelled rows that are not held out; of each label the ``max_examples`` with the smallest id hashes."""
    marked = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("doc_id is not null and toxic in (0, 1)").where(~held_out("doc_id"))
    sizes = {r["toxic"]: r["n"] for r in marked.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    parts = [marked.where(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_examples) for y in (0, 1)]
    chosen = parts[0].unionByName(parts[1])
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(chosen), "doc_id").where(F.coalesce(F.length("text"), F.lit(0)) <= EXAMPLE_CHARS).select("doc_id", "text", "toxic")  # twice max_examples ids at most
    got = sorted(((r["doc_id"], r["text"] or "", r["toxic"]) for r in rows.toLocalIterator()), key=lambda r: (r[0], r[2], r[1]))
    total = sum(sizes.values())
    df, n = document_frequencies(spark, docs, {w for _, t, _ in got for w in _WORD.findall(t.lower())}) if got else ({}, 0)
    return Neighbours(got, sizes.get(1, 0) / total if total else None, df, n)


def scores(spark: SparkSession, docs: DataFrame, model: Neighbours) -> DataFrame:
    """doc_id, score, predicted and evidence (ids of the nearest examples) of every row of ``docs``."""
    shared = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                got = [own.score(t) for t in part.column(1).to_pylist()]
                value = [min(1.0, max(0.0, g[0])) for g in got]
                cols = [part.column(0), pa.array(value, pa.float64()), pa.array([int(v >= 0.5) for v in value], pa.int32()), pa.array([g[1] for g in got], pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "score", "predicted", "evidence"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, score double, predicted int, evidence array<long>")


def clean(spark: SparkSession, docs: DataFrame, model: Neighbours) -> DataFrame:
    """The rows of ``docs`` that are not predicted toxic, with all their columns; scored in place, without a shuffle."""
    shared = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                keep = [not own.score(t)[0] >= 0.5 for t in part.column("text").cast(pa.string()).to_pylist()]
                yield part.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
