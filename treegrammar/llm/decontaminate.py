"""Benchmark decontamination by spaced-seed hashing.

Texts become words (maximal runs of letters and digits, lower case). A seed mask names the word positions of a window
that count; the others are ignored, so a substituted word that falls on an ignored position does not hide a passage.
All windows of the test items and of the documents are hashed under every mask and joined; each hit fixes an offset
between item and document, and the overlap around it is verified word by word, to both sides, tolerating substitutions.

A document is contaminated by an item if the verified overlap has at least ``min_words`` equal words (or all words but
a tenth, for an item shorter than that) with a share of equal words of ``min_share`` or more. The masks miss no such
overlap at the default thresholds: every pattern of substitutions in 8 to 29 words that meets them leaves a hit, and a
longer stretch either begins with 15 words that meet them or meets them without those. Higher thresholds keep this. An item of one to
seven words cannot lose a word and still be told from chance: it must stand in the document whole, and is found by a mask of its own length.

The test side is small against the documents. Its hashes are the build side of the join: they are shipped in blocks of at most ``BLOCK_WORDS`` words, so
what is broadcast has a fixed size; a larger benchmark takes more passes, never a cap. (A shuffled join would move a row for each word
and mask, some sixteen times the input.) Documents are read
whole and stay in place: only verified overlaps leave the tasks, so frequent passages and sources cannot skew a shuffle.

Defined results: null texts count as empty; an item without words matches nothing; several overlaps of a document with one item give one row, the one with most equal words, then the
first; equal items give a row each; repeated rows of a document give one row for each item, that of the best overlap; extra columns are ignored.
``clean`` judges every row by its own text, whatever its id.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Positions that count, of windows of up to twelve words, from a greedy cover of all patterns of substitutions.
MASKS = ((0, 1, 2, 3, 5, 6), (0, 1, 3, 7, 10, 11), (0, 1, 2, 6, 8, 9), (0, 1, 2, 3, 4, 5))
MIN_WORDS, MIN_SHARE = 12, 0.8
#: Words of an item from which substitutions are tolerated.
TOLERANT = 8
BLOCK_WORDS = 400_000
_WORD = re.compile(r"[^\W_]+")


def words(text: str | None) -> list[str]:
    return _WORD.findall((text or "").lower())


def _weights() -> np.ndarray:
    """Odd multipliers for the window positions, from a fixed generator."""
    return np.random.default_rng(20240229).integers(1, 1 << 62, 16, dtype=np.int64).astype(np.uint64) * np.uint64(2) + np.uint64(1)


def window_hashes(ids: np.ndarray, mask: tuple[int, ...]) -> np.ndarray:
    """A hash of every window of ids under a mask; 0 where a counted position holds an unknown word."""
    n = len(ids) - mask[-1]
    if n <= 0:
        return np.empty(0, np.uint64)
    w, total, known = _weights(), np.zeros(n, np.uint64), np.ones(n, bool)
    for k in mask:
        part = ids[k : k + n]
        known &= part != 0
        total += part * w[k]
    total ^= total >> np.uint64(29)
    return np.where(known, total | np.uint64(1), np.uint64(0))


class TestBlock:
    """The words, hashes and positions of a block of test items."""

    __test__ = False

    def __init__(self, items: list[tuple[int, str]]):
        self.vocab: dict[str, int] = {}
        self.items: list[tuple[int, np.ndarray]] = []
        for item, text in items:
            if got := words(text):
                self.items.append((item, np.array([self.vocab.setdefault(w, len(self.vocab) + 1) for w in got], np.uint64)))
        sizes = np.array([len(ids) for _, ids in self.items], np.int64)
        self.shortest = int(sizes.min(initial=TOLERANT))
        plans = [(m, sizes >= TOLERANT) for m in MASKS] + [(tuple(range(n)), sizes == n) for n in range(1, TOLERANT)]
        self.tables = []  # mask, whether the whole item must stand there, distinct hashes, hashes, items, positions
        for k, (mask, fits) in enumerate(plans):
            parts = [(h, np.full(len(h), i), np.arange(len(h))) for i in np.flatnonzero(fits).tolist() if len(h := window_hashes(self.items[i][1], mask))]
            if parts:
                h, i, at = (np.concatenate(x) for x in zip(*parts, strict=True))
                order = np.argsort(h, kind="stable")
                self.tables.append((mask, k >= len(MASKS), np.unique(h), h[order], i[order], at[order]))

    def overlaps(self, text: str | None, min_words: int = MIN_WORDS, min_share: float = MIN_SHARE) -> list[tuple[int, int, int, int, int]]:
        """item_id, equal words, words of the overlap, its first word in the document and in the item."""
        known = self.vocab
        ids = np.array([known.get(w, 0) for w in words(text)], np.uint64)
        if np.count_nonzero(ids) < min(6, self.shortest):
            return []
        seeds: set[tuple[int, int]] = set()
        best: dict[int, tuple[int, int, int, int, int]] = {}
        for mask, whole, unique, hashes, item, at in self.tables:
            mine = window_hashes(ids, mask)
            spot = np.flatnonzero(mine)
            found = np.searchsorted(unique, mine[spot])
            spot = spot[(found < len(unique)) & (unique[np.minimum(found, len(unique) - 1)] == mine[spot])]
            for p in spot.tolist():
                for k in range(int(np.searchsorted(hashes, mine[p], "left")), int(np.searchsorted(hashes, mine[p], "right"))):
                    i, n = int(item[k]), len(mask)
                    if not whole:
                        seeds.add((i, p - int(at[k])))
                    elif i not in best and (ids[p : p + n] == self.items[i][1]).all():
                        best[i] = (self.items[i][0], n, n, p, 0)
        for i, shift in sorted(seeds):
            item_id, own = self.items[i]
            lo, hi = max(0, shift), min(len(ids), shift + len(own))
            start, end, n = densest(ids[lo:hi] == own[lo - shift : hi - shift], min_share)
            if n >= min(min_words, int(np.ceil(0.9 * len(own)))):
                row = (item_id, n, end - start, lo + start, lo - shift + start)
                if i not in best or (-n, row[3]) < (-best[i][1], best[i][3]):
                    best[i] = row
        return [best[i] for i in sorted(best)]


def densest(equal: np.ndarray, min_share: float) -> tuple[int, int, int]:
    """Start, end and equal words of the stretch with most equal words among those with a share of at least ``min_share``.

    With a weight of 1 - share for an equal word and -share for another, such stretches have a sum of zero or more; for every
    start the furthest end is best, found in the running maximum from the right."""
    if not equal.any():
        return 0, 0, 0
    total = np.concatenate([[0.0], np.cumsum(np.where(equal, 1 - min_share, -min_share))]) + 0.0
    ahead = np.maximum.accumulate(total[::-1])[::-1]
    ends = len(ahead) - 1 - np.searchsorted(ahead[::-1], total - 1e-9, side="left")
    count = np.concatenate([[0], np.cumsum(equal)])
    n = count[ends] - count
    start = int(np.argmax(n))
    end = int(ends[start])
    inside = np.flatnonzero(equal[start:end])
    return start + int(inside[0]), start + int(inside[-1]) + 1, int(n[start])


def _blocks(tests: DataFrame) -> Iterator[list[tuple[int, str]]]:
    """Test items in blocks of bounded size, read one partition at a time."""
    block, held = [], 0
    for row in tests.toLocalIterator():
        text, n = row["text"] or "", len(row["text"] or "") // 4 + 1
        if held + n > BLOCK_WORDS and block:
            yield block
            block, held = [], 0
        block.append((row["item_id"], text))
        held += n
    if block:
        yield block


def overlaps(spark: SparkSession, docs: DataFrame, tests: DataFrame, min_words: int = MIN_WORDS, min_share: float = MIN_SHARE) -> DataFrame:
    """doc_id, item_id, equal_words, overlap_words, doc_word, item_word, share of every contaminated document and item."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    tests = tests.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text"))
    schema = "doc_id long, item_id long, equal_words long, overlap_words long, doc_word long, item_word long"
    out = None
    for block in _blocks(tests):
        one = rows.mapInArrow(_found(spark.sparkContext.broadcast(block), min_words, min_share), schema)
        out = one if out is None else out.unionByName(one)
    if out is None:
        out = spark.createDataFrame([], schema)
    best = F.min(F.struct((-F.col("equal_words")).alias("less"), "doc_word", "overlap_words", "item_word")).alias("b")
    out = out.groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", (-F.col("b.less")).alias("equal_words"), "b.overlap_words", "b.doc_word", "b.item_word")
    return out.withColumn("share", F.col("equal_words") / F.col("overlap_words"))


def _found(shared, min_words: int, min_share: float):
    """The overlaps of the rows (doc_id, text) with a block of items."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        test = TestBlock(shared.value)
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                found = [(doc_id, *x) for doc_id, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True) for x in test.overlaps(text, min_words, min_share)]
                cols = list(zip(*found, strict=True)) if found else [[]] * 6
                yield pa.RecordBatch.from_arrays([pa.array(list(c), pa.int64()) for c in cols], names=["doc_id", "item_id", "equal_words", "overlap_words", "doc_word", "item_word"])

    return run


def _without(shared):
    """The rows whose texts share no passage with a block of items."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        test = TestBlock(shared.value)
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                keep = [not test.overlaps(t) for t in part.column("text").cast(pa.string()).to_pylist()]
                yield part.filter(pa.array(keep, pa.bool_()))

    return run


def clean(spark: SparkSession, docs: DataFrame, tests: DataFrame) -> DataFrame:
    """The rows of ``docs`` that share no passage with a test item, with all their columns; judged in place, without a shuffle."""
    for block in _blocks(tests.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text"))):
        docs = docs.mapInArrow(_without(spark.sparkContext.broadcast(block)), docs.schema)
    return docs
