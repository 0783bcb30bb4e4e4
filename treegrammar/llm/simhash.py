"""SimHash near-dedup over pivot distance tables.

The fingerprint of a text is the bitwise majority of the XXH64 values of its three-word shingles. Distinct fingerprints
get a table of Hamming distances to ``PIVOTS`` reference fingerprints, computed once. Two fingerprints that differ in
``d`` bits have distances to any reference that differ by ``d`` at most, so a pair whose largest coordinate difference
exceeds the radius is discarded without comparing the fingerprints; survivors are verified by their exact distance.

Which pairs meet: the table holds the distances by segment too. The 64 bits are cut into five segments; distances to the references
within a segment add up to the whole ones, and a pair within three bits has equal distances to every reference in at least two segments. So the rows
are dealt by the tuples of distances in each of the ten pairs of segments, and no pair within the radius is lost. A group
of more than ``CELL_ROWS`` fingerprints is split into chunks and every pair of chunks becomes a cell of its own, so no
task holds a group without bound; a cell emits a spanning forest of its links, never all pairs. Equal fingerprints are
one node from the start, however many texts share one, and the entries of fingerprints and components with many rows are broadcast (a bounded number).

Defined results: a null text counts as empty; a text without words has fingerprint zero and is linked like any other;
repeated rows of an id are rows of their own; extra columns are ignored; an empty table gives no rows. A null doc_id
gets a fingerprint, and its component is the smallest non-null id reached (null if there is none).
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treegrammar.llm.components import components, forest
from treegrammar.llm.skew import join_entries
from treegrammar.shared import written

SEED, SHINGLE, RADIUS = 42, 3, 3
PIVOTS = 16
CELL_ROWS = 2048
SEGMENTS = ((0, 13), (13, 13), (26, 13), (39, 13), (52, 12))
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def references() -> np.ndarray:
    """The reference fingerprints: XXH64 of their numbers, so every run has the same."""
    return np.array([xxhash.xxh64_intdigest(k.to_bytes(4, "little"), SEED) for k in range(PIVOTS)], np.uint64)


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    words = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    n = len(words)
    if not n:
        return 0
    if n <= shingle:
        return xxhash.xxh64_intdigest(b" ".join(words), SEED)
    line = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, n) + 1) - 1
    starts = [0, *(ends[: n - shingle] + 1).tolist()]
    h = xxhash.xxh64_intdigest
    hashed = np.fromiter((h(line[a:b], SEED) for a, b in zip(starts, ends[shingle - 1 :].tolist(), strict=True)), np.uint64, n - shingle + 1)
    return majority(hashed)


def majority(hashed: np.ndarray) -> int:
    n, ones = len(hashed), np.zeros(64, np.int64)
    for at in range(0, n, 32768):
        part = hashed[at : at + 32768].astype("<u8")
        bits = np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        pad = -len(bits) % 255
        if pad:
            bits = np.concatenate([bits, np.zeros((pad, 64), np.uint8)])
        ones += bits.reshape(-1, 255, 64).sum(axis=1, dtype=np.uint8).sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > n, bitorder="little").view("<u8")[0])


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, 512):
            part = batch.slice(at, 512)
            prints = np.array([fingerprint(t) for t in part.column(1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(prints), part.column(2)], names=["doc_id", "print", "mark"])


def pivot_distances(prints: np.ndarray) -> np.ndarray:
    """(fingerprints, segments, references): the distances to all references within each segment."""
    masks = np.array([((1 << n) - 1) << at for at, n in SEGMENTS], np.uint64)
    return np.bitwise_count((prints[:, None, None] ^ references()) & masks[:, None])


def deal_keys(far: np.ndarray) -> np.ndarray:
    """(fingerprints, pairs of segments): a hash of the tuple of distances in both segments."""
    odd = np.random.default_rng(77).integers(0, 1 << 62, (2, far.shape[2]), dtype=np.int64).astype(np.uint64) * np.uint64(2) + np.uint64(1)
    one = (far[:, :, None, :] * odd).sum(axis=3, dtype=np.uint64)  # (fingerprints, segments, 2)
    pairs = np.array(list(combinations(range(len(SEGMENTS)), 2)))
    key = one[:, pairs[:, 0], 0] * np.uint64(0x9E3779B97F4A7C15) + one[:, pairs[:, 1], 1] + np.arange(len(pairs), dtype=np.uint64)
    key = (key ^ key >> np.uint64(29)) * np.uint64(0xBF58476D1CE4E5B9)
    return (key ^ key >> np.uint64(32)).view(np.int64)


def _table(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The whole pivot distances of each fingerprint, one byte each, and the keys by which it is dealt."""
    for batch in batches:
        for at in range(0, batch.num_rows, 2048):
            part = batch.slice(at, 2048)
            apart = pivot_distances(part.column(0).to_numpy(zero_copy_only=False).view(np.uint64))
            whole, keys = apart.sum(axis=1, dtype=np.uint8), deal_keys(apart.astype(np.uint64))
            packed = pa.array([w.tobytes() for w in whole], pa.binary())
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, keys.size + 1, keys.shape[1]), pa.int32()), pa.array(keys.ravel()))
            yield pa.RecordBatch.from_arrays([part.column(0), packed, lists], names=["print", "far", "keys"])


def linked(prints: np.ndarray, far: np.ndarray, left: np.ndarray, right: np.ndarray, radius: int) -> np.ndarray:
    """Which of the pairs (left, right) survive the pivot table and then the exact distance."""
    keep = np.arange(len(left))
    for k in range(far.shape[1]):
        gap = np.abs(far[left[keep], k].astype(np.int16) - far[right[keep], k])
        keep = keep[gap <= radius]
        if not len(keep):
            return keep
    return keep[np.bitwise_count(prints[left[keep]] ^ prints[right[keep]]) <= radius]


def _cell(prints: np.ndarray, far: np.ndarray, side: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the links in one large cell; side: 0 and 1 if only links between the two chunks are asked for."""
    order = np.argsort(far[:, 0], kind="stable")
    first = far[order, 0].astype(np.int16)
    a, b = [], []
    for at in range(0, len(order), 256):
        block = order[at : at + 256]
        end = np.searchsorted(first, first[min(at + 255, len(order) - 1)] + radius, side="right")
        i, j = np.meshgrid(np.arange(at, at + len(block)), np.arange(at, end), indexing="ij")
        ok = i < j
        i, j = order[i[ok]], order[j[ok]]
        if side.any():
            cross = side[i] != side[j]
            i, j = i[cross], j[cross]
        hit = linked(prints, far, i, j, radius)
        a.append(i[hit])
        b.append(j[hit])
        if sum(map(len, a)) > 500_000:
            x, y = forest(np.concatenate(a), np.concatenate(b))
            a, b = [x], [y]
    return forest(np.concatenate(a), np.concatenate(b)) if a else (np.empty(0, int), np.empty(0, int))


def _links(radius: int):
    def solve(cell: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        number, prints, far, side = cell
        a, b = [], []
        edge = np.flatnonzero(np.concatenate([[True], number[1:] != number[:-1], [True]]))
        sizes = np.diff(edge)
        big = sizes > 48
        for s, e in zip(edge[:-1][big], edge[1:][big], strict=True):
            x, y = _cell(prints[s:e], far[s:e], side[s:e], radius)
            a.append(x + s)
            b.append(y + s)
        of = np.repeat(sizes, sizes)
        small = np.flatnonzero((of > 1) & (of <= 48))
        for d in range(1, int(of[small].max(initial=1))):
            left = small[small + d < len(number)]
            left = left[number[left] == number[left + d]]
            if not len(left):
                break
            hit = linked(prints, far, left, left + d, radius)
            a.append(left[hit])
            b.append(left[hit] + d)
        return (np.concatenate(a), np.concatenate(b)) if a else (np.empty(0, int), np.empty(0, int))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by cell; the last cell of a batch waits for the rest of it."""
        held: list[np.ndarray] | None = None

        def out(cell: list[np.ndarray]) -> pa.RecordBatch:
            x, y = solve(cell)
            prints = cell[1].view(np.int64)
            return pa.RecordBatch.from_arrays([pa.array(prints[x]), pa.array(prints[y])], names=["a", "b"])

        for batch in batches:
            if not batch.num_rows:
                continue
            number = batch.column(0).to_numpy(zero_copy_only=False)
            prints = batch.column(1).to_numpy(zero_copy_only=False).view(np.uint64)
            far = np.frombuffer(b"".join(batch.column(2).to_pylist()), np.uint8).reshape(len(prints), -1)
            side = batch.column(3).to_numpy(zero_copy_only=False).astype(np.int8)
            now = [number, prints, far, side]
            if held is not None:
                now = [np.concatenate(x) for x in zip(held, now, strict=True)]
            cut = int(np.searchsorted(now[0], now[0][-1], side="left")) if (now[0][1:] >= now[0][:-1]).all() else int(len(now[0]) - np.argmax(now[0][::-1] != now[0][-1]))
            if cut:
                yield out([x[:cut] for x in now])
            held = [x[cut:] for x in now]
        if held is not None and len(held[0]):
            yield out(held)

    return run


def print_links(spark: SparkSession, prints: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Links (a, b) between distinct fingerprints ``prints`` (print long) that connect all within ``radius`` <= 3 bits."""
    if radius > 3:
        raise ValueError("five segments cover a radius of three bits at most")
    table = written(spark, prints.select("print").mapInArrow(_table, "print long, far binary, keys array<long>"), "pivots")
    sizes = written(spark, table.select(F.explode("keys").alias("key")).groupBy("key").agg(F.count("*").alias("n")).where("n > 1"), "cells")
    met = join_entries(table.select("print", "far", F.explode("keys").alias("key")), sizes, ["key"], "n", 10 * table.count())
    chunks = F.ceil(F.col("n") / CELL_ROWS).cast("int")
    met = met.withColumn("chunks", chunks).withColumn("own", F.pmod(F.xxhash64("print"), F.col("chunks")).cast("int"))
    met = met.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    cell = F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other"))
    met = met.select(cell.alias("cell"), "print", "far", (F.col("own") > F.col("other")).cast("byte").alias("side"))
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return met.repartition(n, "cell").sortWithinPartitions("cell").mapInArrow(_links(radius), "a long, b long").distinct()


_BIG = (1 << 63) - 1


def _named(spark: SparkSession, docs: DataFrame, radius: int) -> DataFrame:
    """doc_id, print, mark (a digest of the text), component_id, and the row that stays for its component: keep_id, keep_mark."""
    text = F.col("text").cast("string")
    mark = F.sha2(F.coalesce(text, F.lit("")).cast("binary"), 256).alias("mark")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"), mark)
    prints = written(spark, rows.mapInArrow(_fingerprints, "doc_id long, print long, mark string"), "prints")
    least = F.min(F.struct(F.coalesce("doc_id", F.lit(_BIG)).alias("id"), "mark"))
    nodes = written(spark, prints.groupBy("print").agg(least.alias("least"), F.count("*").alias("n")), "print-nodes")
    joined = components(spark, print_links(spark, nodes, radius))  # over fingerprints
    rooted = nodes.join(joined.select(F.col("node").alias("print"), "root"), "print", "left").select("print", "least", "n", F.coalesce("root", "print").alias("root"))
    rooted = written(spark, rooted, "print-roots")
    best = written(spark, rooted.groupBy("root").agg(F.min("least").alias("best"), F.count("*").alias("prints")), "root-entries")
    named = written(spark, join_entries(rooted.select("print", "n", "root"), best, ["root"], "prints", nodes.count()).select("print", "n", "best"), "print-entries")
    keep_id = F.when(F.col("best.id") != _BIG, F.col("best.id"))
    return join_entries(prints, named, ["print"], "n", prints.count()).select("doc_id", "print", "mark", keep_id.alias("component_id"), F.col("best.mark").alias("keep_mark"))


def near_components(spark: SparkSession, docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """doc_id, fingerprint and component_id of every row of ``docs`` (doc_id, text)."""
    return _named(spark, docs, radius).select("doc_id", F.lpad(F.lower(F.hex("print")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """One row of every component, with all its columns: that with the smallest id (null last), of these the one whose text has the smallest digest."""
    found = _named(spark, docs, RADIUS).where("doc_id <=> component_id and mark = keep_mark")
    found = written(spark, found.groupBy(F.col("doc_id").alias("__keep"), F.col("mark").alias("__mark")).agg(F.count("*").alias("repeats")), "representatives")
    mark = F.sha2(F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary"), 256)
    same = F.col("doc_id").cast("long").eqNullSafe(F.col("__keep")) & (mark == F.col("__mark"))
    again = found.where("repeats > 1")
    if again.isEmpty():
        return docs.join(found, same, "left_semi")
    one = docs.join(again, same, "left_semi").withColumn("__mark", mark).dropDuplicates(["doc_id", "__mark"]).drop("__mark")
    return docs.join(found.where("repeats = 1"), same, "left_semi").unionByName(one)
