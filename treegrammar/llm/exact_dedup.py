"""Exact dedup with a log-structured merge index of digests.

Texts count as equal when they are the same bytes after every character of ``[\\x20\\x09-\\x0D]`` is deleted.
Every task fills a memtable (digest -> best row, count) and flushes it as a digest-sorted run; runs are Parquet files below the shared
folder. Compaction merges all runs: for each digest the row with the most code points, then the smallest identifier stays. The
index has a Bloom filter for each digest prefix, over the digests that were seen often enough to matter. Every document is looked up
in the filters; the hits give up their bytes, which are grouped by digest and bytes. A digest with a single group is
verified; the rows of another (a collision) are told apart by their bytes, so the result is exact.

Hot groups: memtables pre-aggregate, so a digest reaches compaction once a task at most, and equal bytes are merged in the task before
they are shuffled; the entries of hot digests are broadcast (a bounded number), so their rows stay where they are. A pass over the texts ships
filters of at most ``MAX_FILTER_BYTES``; more repeated digests take more passes over the prefixes, never a filter less.

Defined results: a null text counts as empty, empty and blank texts are equal to each other, a null id is a value like any
other that sorts after all of them, repeated rows of one id count each and one of them stays, extra columns are ignored, an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from treegrammar.llm.skew import join_entries
from treegrammar.shared import new_path, written

BLANK = bytes([0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D])
#: Documents of a memtable before it is flushed.
MEMTABLE_ROWS = 200_000
#: The Bloom filters: bits for each key, hash functions, digest prefixes, and the bytes of filters that one pass ships.
BITS_PER_KEY, HASHES, PREFIXES, MAX_FILTER_BYTES = 16, 8, 4096, 32 << 20
_BIG = (1 << 63) - 1
DIGESTS = "row long, doc_id long, digest binary, n_points long"
RUNS = "prefix int, digest binary, n_points long, keep_id long, keep_row long, n_rows long"


def normal_bytes(text: str | None) -> bytes:
    return (text or "").encode("utf-8", "surrogatepass").translate(None, BLANK)


def prefix_of(digest: bytes) -> int:
    return (digest[0] << 8 | digest[1]) % PREFIXES


def _digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, 1024):
            part = batch.slice(at, 1024)
            texts = part.column(2).to_pylist()
            hashed = [hashlib.sha256(normal_bytes(t)).digest() for t in texts]
            points = [len(t) if t else 0 for t in texts]
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(hashed, pa.binary()), pa.array(points, pa.int64())], names=["row", "doc_id", "digest", "n_points"])


def _rows(docs: DataFrame) -> DataFrame:
    return docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def digests(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """row (a key of its own), doc_id, digest, n_points of every row of ``docs`` (doc_id, text), written once."""
    return written(spark, _rows(docs).mapInArrow(_digests, DIGESTS), "digests")


def _flush_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Memtables of this task, flushed as sorted runs: digest, points, id and key of the best row, rows."""
    table: dict[bytes, tuple[int, int, int, int]] = {}

    def run() -> pa.RecordBatch:
        keys = sorted(table)
        rows = [table[k] for k in keys]
        cols = [[prefix_of(k) for k in keys], keys, [-r[0] for r in rows], [None if r[1] == _BIG else r[1] for r in rows], [r[2] for r in rows], [r[3] for r in rows]]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int32(), pa.binary(), *[pa.int64()] * 4), strict=True)], names=["prefix", "digest", "n_points", "keep_id", "keep_row", "n_rows"])

    for batch in batches:
        for row, doc_id, digest, points in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
            mine = (-points, _BIG if doc_id is None else doc_id, row)
            old = table.get(digest)
            table[digest] = (*mine, 1) if old is None else (*min(mine, old[:3]), old[3] + 1)
            if len(table) >= MEMTABLE_ROWS:
                yield run()
                table.clear()
    if table:
        yield run()


def _best() -> Column:
    """Of several rows the one with most points, then the smallest id (null last), then the smallest key."""
    return F.min(F.struct((-F.col("n_points")).alias("less"), F.coalesce("keep_id", F.lit(_BIG)).alias("id"), F.col("keep_row").alias("row")))


def _merged(runs: DataFrame) -> DataFrame:
    one = runs.groupBy("prefix", "digest").agg(_best().alias("best"), F.sum("n_rows").alias("n_rows"))
    return one.select("prefix", "digest", (-F.col("best.less")).alias("n_points"), F.when(F.col("best.id") != _BIG, F.col("best.id")).alias("keep_id"), F.col("best.row").alias("keep_row"), "n_rows")


class DigestIndex:
    """Sorted runs (``RUNS``) below one folder, each set of runs with the Bloom filters of its prefixes.

    ``insert`` flushes a batch to level 0; ``compact`` merges all runs and the level below into a new level 1; ``lookup`` joins
    only the probes that some filter lets pass. The filters hold the digests with ``least`` rows or more: one for probes
    of other batches, two where a batch is compared with itself."""

    def __init__(self, spark: SparkSession, least: int = 1):
        self.spark, self.least = spark, least
        self.runs: list[tuple[str, str]] = []  # paths of the runs and of their filters
        self.base: tuple[str, str] | None = None

    def _with_filters(self, path: str) -> tuple[str, str]:
        own = self.spark.read.parquet(path).where(F.col("n_rows") >= self.least).select("prefix", "digest")
        filters = new_path(self.spark, "lsm-filters")
        own.repartition("prefix").sortWithinPartitions("prefix").mapInArrow(_filters, "prefix int, words binary").write.parquet(filters)
        return path, filters

    def insert(self, batch: DataFrame) -> None:
        """Flush the memtables of a batch of documents (``DIGESTS``) as new runs."""
        path = new_path(self.spark, "lsm-level0")
        batch.select("row", "doc_id", "digest", "n_points").mapInArrow(_flush_runs, RUNS).write.parquet(path)
        # A digest that is new to every run of a batch may still be in two of them, so runs are merged before they are asked for repeats.
        self.runs.append(self._with_filters(path) if self.least == 1 else (path, ""))

    def compact(self) -> DataFrame:
        """Merge all runs and the level below; of each digest the longest row with the smallest identifier stays."""
        if self.runs:
            parts = [p for p, _ in self.runs] + ([self.base[0]] if self.base else [])
            path = new_path(self.spark, "lsm-level1")
            _merged(self.spark.read.parquet(*parts)).sortWithinPartitions("prefix", "digest").write.parquet(path)
            self.base, self.runs = self._with_filters(path), []
        return self.spark.read.parquet(self.base[0])

    def passes(self) -> Iterator[tuple[int, int, dict[int, list[bytes]]]]:
        """Ranges of prefixes that cover all of them, and their filters: at most ``MAX_FILTER_BYTES`` of them at once (one prefix at least)."""
        sets = [f for _, f in [*self.runs, *([self.base] if self.base else [])]]
        every = self.spark.read.schema("prefix int, words binary").parquet(*sets)
        sizes = {r["prefix"]: r["n"] for r in every.groupBy("prefix").agg(F.sum(F.octet_length("words")).alias("n")).collect()}  # PREFIXES rows at most
        start = held = 0
        for prefix in range(PREFIXES + 1):
            more = sizes.get(prefix, 0)
            if prefix == PREFIXES or held and held + more > MAX_FILTER_BYTES:
                got: dict[int, list[bytes]] = {}
                for r in every.where((F.col("prefix") >= start) & (F.col("prefix") < prefix)).collect():
                    got.setdefault(r["prefix"], []).append(bytes(r["words"]))
                yield start, prefix, got
                start, held = prefix, 0
            held += more

    def hits(self, rows: DataFrame) -> DataFrame:
        """row, doc_id, digest, n_points and normal bytes of the rows (row, doc_id, text) that some filter lets pass."""
        out = None
        for _, _, filters in self.passes():
            one = rows.mapInArrow(_hits(self.spark.sparkContext.broadcast(filters)), DIGESTS + ", body binary")
            out = one if out is None else out.unionByName(one)
        return out

    def lookup(self, probes: DataFrame) -> DataFrame:
        """The entry of every probed digest (doc_id, digest): doc_id, digest, keep_id and rows seen (null where the index has none)."""
        sets = [p for p, _ in [*self.runs, *([self.base] if self.base else [])]]
        probe = probes.select("doc_id", "digest")
        none = [F.lit(None).cast("long").alias(c) for c in ("keep_id", "n_rows")]
        if not sets:
            return probe.select("*", *none)
        seen = _merged(self.spark.read.parquet(*sets)).select("digest", "keep_id", "n_rows")
        marked = None
        for start, end, filters in self.passes():
            one = probe.mapInArrow(_tested(start, end, self.spark.sparkContext.broadcast(filters)), "doc_id long, digest binary, maybe boolean")
            marked = one if marked is None else marked.unionByName(one)
        joined = marked.where("maybe").join(seen, "digest", "left").select("doc_id", "digest", "keep_id", "n_rows")
        return joined.unionByName(marked.where("not maybe").select("doc_id", "digest", *none))


def _positions(digests: list[bytes], bits: int) -> np.ndarray:
    """Bit positions (rows, HASHES) of digests in a filter of that many bits."""
    two = np.frombuffer(b"".join(d[8:24] for d in digests), "<u8").reshape(-1, 2)
    step = two[:, 1:] | np.uint64(1)
    return (two[:, :1] + step * np.arange(HASHES, dtype=np.uint64)) % np.uint64(bits)


def bloom_filter(digests: list[bytes]) -> bytes:
    """The filter of some digests: as many words of 64 bits as they need, a power of two."""
    bits = max(64, 1 << (len(digests) * BITS_PER_KEY - 1).bit_length())
    p = _positions(digests, bits).ravel()
    words = np.zeros(bits // 64, np.uint64)
    np.bitwise_or.at(words, (p >> np.uint64(6)).astype(np.int64), np.uint64(1) << (p & np.uint64(63)))
    return words.tobytes()


def passes(filter_: bytes, digests: list[bytes]) -> np.ndarray:
    """Which digests a filter lets pass."""
    words = np.frombuffer(filter_, np.uint64)
    p = _positions(digests, len(words) * 64)
    return ((words[p >> np.uint64(6)] >> (p & np.uint64(63))) & np.uint64(1)).all(axis=1)


def passing(filters: dict[int, list[bytes]], digests: list[bytes]) -> list[int]:
    """The numbers of the digests that a filter of their prefix lets pass."""
    by: dict[int, list[int]] = {}
    for i, d in enumerate(digests):
        if (p := prefix_of(d)) in filters:
            by.setdefault(p, []).append(i)
    out = []
    for p, some in by.items():
        own = [digests[i] for i in some]
        hit = np.any([passes(f, own) for f in filters[p]], axis=0)
        out += [i for i, h in zip(some, hit.tolist(), strict=True) if h]
    return sorted(out)


def _filters(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (prefix, digest) come sorted by prefix: one filter for each."""

    def out(prefix: int, held: list[bytes]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([prefix], pa.int32()), pa.array([bloom_filter(held)], pa.binary())], names=["prefix", "words"])

    now, held = None, []
    for batch in batches:
        for prefix, digest in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            if prefix != now and held:
                yield out(now, held)
                held = []
            now = prefix
            held.append(digest)
    if held:
        yield out(now, held)


def _tested(start: int, end: int, filters):
    """The probes whose prefixes lie in a range, and whether a filter lets them pass."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            mine = b.filter(pa.array([start <= prefix_of(d) < end for d in b.column(1).to_pylist()], pa.bool_()))
            hit = np.zeros(mine.num_rows, bool)
            hit[passing(filters.value, mine.column(1).to_pylist())] = True
            yield pa.RecordBatch.from_arrays([mine.column(0), mine.column(1), pa.array(hit)], names=["doc_id", "digest", "maybe"])

    return run


def _hits(filters):
    """Rows that pass a filter, with their normal text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                texts = part.column(2).to_pylist()
                normal = [normal_bytes(t) for t in texts]
                hashed = [hashlib.sha256(t).digest() for t in normal]
                pick = passing(filters.value, hashed)
                cols = [pa.array([hashed[i] for i in pick], pa.binary()), pa.array([len(texts[i] or "") for i in pick], pa.int64()), pa.array([normal[i] for i in pick], pa.binary())]
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(pick, pa.int64())), part.column(1).take(pa.array(pick, pa.int64())), *cols], names=["row", "doc_id", "digest", "n_points", "body"])

    return run


GROUPS = ("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def exact_groups(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 of every row of ``docs`` (doc_id, text)."""
    return _groups(spark, docs).select(*GROUPS)


def _groups(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """The columns of ``exact_groups``, n_points, and whether the row is the one that stays or a repeat of it."""
    own = digests(spark, docs)
    index = DigestIndex(spark, least=2)
    index.insert(own)
    repeated = index.compact().where("n_rows > 1").select("digest", F.col("n_points").alias("best_points"), "keep_id", "keep_row", "n_rows")
    # The bytes of the hits, merged in their tasks before they are shuffled: more than one text of a digest is a collision.
    bodies = index.hits(_rows(docs)).groupBy("digest", "body").agg(F.count("*").alias("copies"))
    collided = written(spark, bodies.groupBy("digest").agg(F.count("*").alias("texts")).where("texts > 1").select("digest"), "collided")
    found = join_entries(own, repeated, ["digest"], "n_rows", own.count(), "left")
    first = F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("n_points") == F.col("best_points"))
    shown = [
        "doc_id", F.when(F.col("n_rows").isNull(), F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"), F.coalesce("n_rows", F.lit(1)).cast("long").alias("group_size"),
        (F.col("n_rows").isNull() | (F.col("row") == F.col("keep_row"))).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"), "n_points", (F.col("n_rows").isNull() | first).alias("first"),
    ]
    if collided.isEmpty():
        return found.select(*shown)
    odd = written(spark, index.hits(_rows(docs)).join(collided, "digest"), "collided-rows")
    best = odd.withColumn("keep_id", F.col("doc_id")).withColumn("keep_row", F.col("row")).groupBy("digest", "body").agg(_best().alias("best"), F.count("*").alias("n_rows"))
    told = odd.join(best, ["digest", "body"]).select("*", F.when(F.col("best.id") != _BIG, F.col("best.id")).alias("keep_id"), F.col("best.row").alias("keep_row"), (-F.col("best.less")).alias("best_points"))
    return found.join(collided, "digest", "left_anti").select(*shown).unionByName(told.select(*shown))


def keep_first(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns: those whose id, digest and length have the flag, and of repeats of such a row one."""
    groups = _groups(spark, docs).where("first").groupBy("doc_id", "text_sha256", "n_points").agg(F.count("*").alias("repeats"))
    kept = written(spark, groups.select(F.col("doc_id").alias("__keep"), F.col("text_sha256").alias("__sha"), F.col("n_points").alias("__points"), "repeats"), "kept")
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    sha = F.sha2(F.translate(text, BLANK.decode(), "").cast("binary"), 256)
    same = F.col("doc_id").cast("long").eqNullSafe(F.col("__keep")) & (sha == F.col("__sha")) & (F.length(text) == F.col("__points"))
    again = kept.where("repeats > 1")
    if again.isEmpty():
        return docs.join(kept, same, "left_semi")
    one = docs.join(again, same, "left_semi").withColumn("__sha", sha).dropDuplicates(["doc_id", "__sha"]).drop("__sha")
    return docs.join(kept.where("repeats = 1"), same, "left_semi").unionByName(one)
