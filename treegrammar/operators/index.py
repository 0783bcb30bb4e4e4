"""Building, loading and querying a sharded grammar index with DataFrames.

A shard is a bounded run of records, compressed in one task. Its row holds the packed rules, the start, the tables and,
apart, the texts, so a count query reads neither tables it does not need nor texts. Queries ship the small automaton
to the tasks, leave out shards whose labels cannot matter by a pushed-down filter, and aggregate a row for each
document or shard. Results of a giant document are put together by its spine, which has a handful of elements.
"""

from __future__ import annotations

import json
import resource
import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treegrammar.grammar.compress import COMPRESSORS, no_start_rule
from treegrammar.grammar.dictionary import pairs_with, train
from treegrammar.grammar.model import Grammar, pack, unpack
from treegrammar.operators.prefix import before
from treegrammar.shared import new_path, written
from treegrammar.sources.carriers import Carrier, Spine
from treegrammar.sources.markup import forest_of, node_table
from treegrammar.views.chunkwise import Chunkwise, Renderer, render, subtree_ends
from treegrammar.views.nodewise import Cursor
from treegrammar.views.rulewise import Run
from treegrammar.xpath.automaton import Automaton, compile_path
from treegrammar.xpath.parse import FOLLOWING, parse_path

#: Structure nodes that a shard aims at.
SHARD_NODES = 500_000
#: Shards whose places in a giant document are shipped with a task (some ten bytes each) instead of joined.
SHIPPED_SHARDS = 50_000
#: Bytes of a row group of the index, about. Writers and readers hold one of them, not all the shards of a task.
ROW_GROUP_BYTES = 16 << 20

SHARD_SCHEMA = (
    "carrier string, section int, shard_no long, variant string, kinds array<int>, names array<string>, labels array<string>, rules array<long>, start array<int>, open_end boolean,"
    " doc_ids array<long>, doc_start array<int>, n_elem long, n_text long, n_node long, elem_chunks array<int>, text_chunks array<int>, jump array<long>, spine_bits binary,"
    " start_close array<int>, start_bp binary, skip_elem array<int>, skip_text array<int>, doc_texts array<int>, texts array<string>, text_bytes long,"
    " t_structure double, t_compress double, t_tables double, peak_mb double"
)
CORE = ["carrier", "section", "shard_no", "kinds", "names", "rules", "start", "open_end", "doc_ids", "doc_start"]


def assign_shards(records: DataFrame, target_nodes: int = SHARD_NODES) -> DataFrame:
    """Add shard_no: contiguous runs in the order of ``ord`` within a section, cut by size through a small table of key buckets.

    Buckets split a section's range of keys evenly; one that holds more than a shard, as keys are dense there, is split by its own range
    again until none does. So no shard exceeds twice the target but for a larger record. Records of one key have no order among them and are dealt by a hash."""
    spark = records.sparkSession
    size = (F.length("content") - F.length(F.replace("content", F.lit("<"), F.lit(""))) + 2).cast("long")
    sized = records.withColumn("size", F.coalesce(size, F.lit(2).cast("long"))).withColumn("bucket", F.lit(0).cast("long"))
    # Key buckets that hold about a sixteenth of a shard on average.
    width = F.greatest(F.lit(1.0), (F.col("hi") - F.col("lo") + 1) * F.lit(target_nodes / 16.0) / F.greatest(F.col("n"), F.lit(1)))
    cut = ["section", "bucket", F.col("lo").alias("__lo"), F.floor(width).cast("long").alias("__width")]
    within = F.col("__lo") + F.floor((F.col("ord") - F.col("__lo")) / F.col("__width")) * F.col("__width")
    totals = lambda df: df.groupBy("section", "bucket").agg(F.sum("size").alias("n"), F.min("ord").alias("lo"), F.max("ord").alias("hi"))
    placed = sized.join(F.broadcast(totals(sized).select(*cut)), ["section", "bucket"]).withColumn("bucket", within).drop("__lo", "__width")  # a row for each section
    while True:
        buckets = written(spark, totals(placed), "key-buckets")
        heavy = buckets.where((F.col("n") > target_nodes) & (F.col("lo") < F.col("hi")))
        if heavy.isEmpty():
            break
        # At most one row for each shard; Spark broadcasts them if they are few.
        placed = placed.join(heavy.select(*cut), ["section", "bucket"], "left").withColumn("bucket", F.coalesce(within, F.col("bucket"))).drop("__lo", "__width")
    numbered = before(buckets, "section", "bucket", {"nodes_before": "n"})
    numbered = numbered.select("section", "bucket", F.floor(F.col("nodes_before") / target_nodes).alias("shard_no"), F.ceil(F.col("n") / target_nodes).alias("parts"))
    dealt = F.when(F.col("parts") > 1, F.pmod(F.xxhash64("doc_id", "content"), F.col("parts"))).otherwise(0)
    return placed.join(numbered, ["section", "bucket"]).withColumn("shard_no", (F.col("shard_no") + dealt).cast("long")).drop("size", "bucket", "parts")


def _bits(events: np.ndarray) -> bytes:
    return np.packbits(events, bitorder="little").tobytes()


def start_parentheses(g: Grammar) -> np.ndarray:
    """The shape of the start as balanced parentheses: True opens a node."""
    ends = g.start_ends()
    out = np.zeros(2 * len(ends), bool)
    closed_before = np.bincount(ends, minlength=len(ends) + 1)
    place = np.arange(len(ends)) + np.cumsum(closed_before)[: len(ends)]
    out[place] = True
    return out


def shard_row(key: tuple, rows: list[tuple[int, str | None]], policy: str, spine: bool, compressor: str, max_rank: int, rules: list | None = None) -> dict:
    """One index row of the records of a shard, in order. With a spine they form a single run of siblings."""
    t0 = time.perf_counter()
    forest = forest_of(rows, policy)
    events, doc_start = forest.arrays()
    if spine:
        doc_start = np.array([0, len(events)], np.int64)
    t1 = time.perf_counter()
    compress = COMPRESSORS[compressor] if rules is None else pairs_with(rules)
    g = compress(forest.names, events, doc_start, spine, max_rank)
    t2 = time.perf_counter()
    chunk = {}
    for kind in ("elem", "text"):
        c = g.chunks(kind)[g.first_rule :]
        chunk[kind] = c[np.arange(c.shape[1])[None, :] <= g.rank[g.first_rule :][:, None]].tolist()
    row = {
        "carrier": key[0], "section": key[1], "shard_no": key[2], "variant": f"{compressor}/{max_rank}", "kinds": [k for k, _ in g.names], "names": [n for _, n in g.names],
        "labels": sorted({n for _, n in g.names}), "rules": pack(g), "start": g.start.astype(np.int32), "open_end": g.open_end, "doc_ids": [0] if spine else forest.doc_ids,
        "doc_start": g.doc_start.tolist(), "n_elem": int(g.totals("elem").sum()), "n_text": int(g.totals("text").sum()), "n_node": int(g.totals("node").sum()), "elem_chunks": chunk["elem"],
        "text_chunks": chunk["text"], "jump": g.masks().view(np.int64).ravel(), "spine_bits": _bits(g.on_spine()), "start_close": g.start_ends().astype(np.int32),
        "start_bp": _bits(start_parentheses(g)), "skip_elem": g.start_skips("elem").astype(np.int32), "skip_text": g.start_skips("text").astype(np.int32), "doc_texts": [0] if spine else forest.doc_texts,
        "texts": forest.texts, "text_bytes": sum(len(t.encode()) for t in forest.texts),
    }
    row |= {"t_structure": t1 - t0, "t_compress": t2 - t1, "t_tables": time.perf_counter() - t2, "peak_mb": resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024}
    return row


#: Records that a dictionary is learned from, about, and characters of markup at most.
SAMPLE_RECORDS, SAMPLE_CHARS = 400, 8_000_000


def learn_dictionary(records: DataFrame, policy: str, size: int, max_rank: int) -> list:
    """Rules learned on a sample of records that a hash of their keys chooses."""
    n = records.count()
    draw = F.pmod(F.xxhash64("section", "ord"), F.lit(1 << 30)) / F.lit(float(1 << 30))
    chosen = records.where((draw < min(1.0, SAMPLE_RECORDS / max(1, n))) & F.col("content").isNotNull()).select("section", "ord", "content")
    rows, held = [], 0
    for r in chosen.toLocalIterator():
        held += len(r["content"])
        if held > SAMPLE_CHARS:
            break
        rows.append((r["section"], r["ord"], r["content"]))
    forest = forest_of([(k, c) for k, (_, _, c) in enumerate(sorted(rows))], policy)
    events, doc_start = forest.arrays()
    return train(forest.names, events, doc_start, size, max_rank)


def writing() -> dict[str, str]:
    """Options of Parquet for rows that are shards: sizes are looked at after every row, where the default waits for a hundred."""
    check = {f"parquet.{what}.size.row.check.{end}": "1" for what in ("page", "block") for end in ("min", "max")}
    return check | {"parquet.block.size": str(ROW_GROUP_BYTES)}


def load_shard(row: dict) -> Grammar:
    """The grammar of an index row that has at least the columns ``CORE``."""
    names = list(zip(map(int, row["kinds"]), row["names"], strict=True))
    outer, hole, inner, rank = unpack(np.asarray(row["rules"], np.int64), len(names))
    return Grammar(names, outer, hole, inner, rank, np.asarray(row["start"], np.int64), np.asarray(row["doc_start"], np.int64), bool(row["open_end"]))


def _shards(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """Rows of a batch; lists of numbers stay numpy views of the Arrow buffers."""
    for batch in batches:
        for k in range(batch.num_rows):
            row = {}
            for name, column in zip(batch.schema.names, batch.columns, strict=True):
                if pa.types.is_list(column.type) and pa.types.is_integer(column.type.value_type) and column.is_valid()[k].as_py():
                    row[name] = column[k].values.to_numpy(zero_copy_only=False)
                else:
                    row[name] = column[k].as_py()
            yield row


def _place(row: dict, places: dict | None) -> tuple[int | None, int, int, int]:
    """Entry state of a shard, and elements, nodes and texts before it."""
    if places is not None:
        return places[row["section"], row["shard_no"]]
    return row.get("q_in"), row.get("e0") or 0, row.get("n0") or 0, row.get("t0") or 0


def _batch(rows: list[tuple], names: list[str], types: list[pa.DataType]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) if rows else [[]] * len(names)
    return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, types, strict=True)], names=names)


class TreeIndex:
    """An index of one carrier: a DataFrame of shards and, for a giant document, its spine."""

    def __init__(self, spark: SparkSession, shards: DataFrame, name: str, spine: Spine | None = None, path: str | None = None):
        self.spark, self.shards, self.name, self.spine, self.path = spark, shards, name, spine, path
        self._totals: dict[int, tuple[int, int, int]] | None = None
        self._places: dict[tuple[int, int], tuple[int, int, int]] | None = None

    # Build, save, load

    @staticmethod
    def build(spark: SparkSession, source: Carrier, path: str | None = None, compressor: str = "pairs", max_rank: int = 2, shard_nodes: int = SHARD_NODES, dictionary: int = 0) -> TreeIndex:
        """Compress the carrier's records into shards and write them; one shuffle by shard.

        With ``dictionary`` so many rules are learned on a sample of records first, of bounded size, and applied to all shards."""
        has_spine, policy, name = source.spine is not None, source.policy, source.name
        records = written(spark, source.records, f"records-{name}") if source.costly else source.records
        numbered = assign_shards(records, shard_nodes)
        rules = learn_dictionary(records, policy, dictionary, max_rank) if dictionary else None

        def make(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
            table = table.sort_by([("ord", "ascending")])
            rows = list(zip(table.column("doc_id").to_pylist(), table.column("content").to_pylist(), strict=True))
            row = shard_row((name, *(k.as_py() for k in key)), rows, policy, has_spine, compressor, max_rank, rules)
            return pa.Table.from_pylist([row], schema=ARROW_SCHEMA)

        out = numbered.select("section", "shard_no", "ord", "doc_id", "content").groupBy("section", "shard_no").applyInArrow(make, SHARD_SCHEMA)
        path = path or new_path(spark, f"index-{source.name}")
        out.write.mode("overwrite").options(**writing()).parquet(path)
        manifest = {"name": source.name, "spine": _spine_json(source.spine), "version": 1}
        spark.createDataFrame([(json.dumps(manifest),)], "manifest string").write.mode("overwrite").parquet(path + "-manifest")
        return TreeIndex.load(spark, path)

    @staticmethod
    def compared(spark: SparkSession, source: Carrier, variants: list[tuple[str, int]], shard_nodes: int = SHARD_NODES) -> DataFrame:
        """(carrier, section, shard_no, variant, ...) as ``stats``, of every shard under each compressor and rank, without keeping an index.

        The records are cut, shuffled and read as markup once for all variants."""
        from treegrammar.measure import STATS_SCHEMA, shard_stats

        spine, policy, name = source.spine is not None, source.policy, source.name
        records = written(spark, source.records, f"records-{name}") if source.costly else source.records

        def make(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
            table = table.sort_by([("ord", "ascending")])
            forest = forest_of(list(zip(table.column("doc_id").to_pylist(), table.column("content").to_pylist(), strict=True)), policy)
            events, doc_start = forest.arrays()
            if spine:
                doc_start = np.array([0, len(events)], np.int64)
            rows, made = [], {}
            for c, r in variants:
                if c == "no_start" and ("pairs", r) in made:
                    g = no_start_rule(made["pairs", r])
                else:
                    g = COMPRESSORS[c](forest.names, events, doc_start, spine, r)
                if c == "pairs":
                    made[c, r] = g
                rows.append(shard_stats(g))
            out = pa.Table.from_pylist(rows)
            keys = [pa.array([v] * len(rows), t) for v, t in ((name, pa.string()), (key[0].as_py(), pa.int32()), (key[1].as_py(), pa.int64()))]
            return pa.table([*keys, pa.array([f"{c}/{r}" for c, r in variants]), *out.columns], ["carrier", "section", "shard_no", "variant", *out.column_names])

        cut = assign_shards(records, shard_nodes).select("section", "shard_no", "ord", "doc_id", "content")
        return cut.groupBy("section", "shard_no").applyInArrow(make, "carrier string, section int, shard_no long, variant string, " + STATS_SCHEMA)

    @staticmethod
    def load(spark: SparkSession, path: str) -> TreeIndex:
        manifest = json.loads(spark.read.parquet(path + "-manifest").first()["manifest"])
        return TreeIndex(spark, spark.read.schema(SHARD_SCHEMA).parquet(path), manifest["name"], _spine_of(manifest["spine"]), path)

    # Helpers

    def _pruned(self, automaton: Automaton) -> DataFrame:
        """Shards that may hold a result: all named labels must occur in a shard of documents, the last one in a run."""
        steps = automaton.steps
        named = [s.name for s in steps if s.name is not None]
        if self.spine is None:
            out = self.shards
            for n in dict.fromkeys(named):
                out = out.where(F.array_contains("labels", n))
            return out
        if steps[-1].name is not None and not any(s.axis == FOLLOWING for s in steps):
            return self.shards.where(F.array_contains("labels", steps[-1].name))
        return self.shards

    def spine_plan(self, automaton: Automaton) -> SpinePlan:
        return SpinePlan(self.spine, automaton)

    # Counting

    def behaviours(self, path: str, jump: bool = True, relevance: str = "fine", skip: bool = True, mode: str = "eager", prune: bool = True) -> DataFrame:
        """Rows (section, shard_no, doc_id, q_in, n, q_out, visited, jumped, skipped, memo_hits, memo) of every shard, document and entry state.

        The counters of a shard stand at its first document and last state; memo: the (rule, state) pairs it keeps."""
        a = compile_path(path)
        plan = self.spine_plan(a) if self.spine else None
        entry = plan.entry if plan else {}
        following = any(s.axis == FOLLOWING for s in a.steps)
        every = following and plan is not None
        src = self._pruned(a) if prune else self.shards
        if plan is not None and not every:
            src = src.where(F.col("section").isin([s for s, q in entry.items() if q != a.universal]))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _shards(batches):
                g = load_shard(row)
                r = Run(g, a, jump, relevance == "fine", skip)
                states = range(a.n_states) if every else [entry.get(row["section"], a.initial)]
                out = []
                for at, q in enumerate(states, 1):
                    n, last = r.eager_count(q) if mode == "eager" else r.lazy_count(q)
                    c = r.count
                    for k, d in enumerate(row["doc_ids"].tolist()):
                        extra = (c.visited, c.jumped, c.skipped, c.memo_hits, len(r._memo)) if k == 0 and at == len(states) else (0,) * 5
                        out.append((row["section"], row["shard_no"], d, q, int(n[k]), last, *extra))
                yield _batch(out, ["section", "shard_no", "doc_id", "q_in", "n", "q_out", "visited", "jumped", "skipped", "memo_hits", "memo"], [pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int32(), *[pa.int64()] * 5])

        return src.select(*CORE).mapInArrow(run, "section int, shard_no long, doc_id long, q_in int, n long, q_out int, visited long, jumped long, skipped long, memo_hits long, memo long")

    def count(self, path: str, by: str = "carrier", **options) -> DataFrame:
        """(n) of the carrier, or (doc_id, n) of every document, zeros included."""
        a = compile_path(path)
        rows = self.behaviours(path, **options)
        if self.spine is not None:
            plan = self.spine_plan(a)
            if any(s.axis == FOLLOWING for s in a.steps):
                total = F.lit(plan.selected_count()).cast("long") + F.coalesce(F.sum("n"), F.lit(0))
                return compose(rows, plan).agg(total.alias("n"))
            return rows.agg((F.coalesce(F.sum("n"), F.lit(0)) + plan.selected_count()).cast("long").alias("n"))
        if by == "carrier":
            return rows.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))
        every = self.shards.select(F.explode("doc_ids").alias("doc_id"))
        got = rows.groupBy("doc_id").agg(F.sum("n").alias("n"))
        return every.join(got, "doc_id", "left").select("doc_id", F.coalesce("n", F.lit(0)).cast("long").alias("n"))

    def count_many(self, paths: list[str]) -> DataFrame:
        """(path, n) of several paths without sibling steps across shards in one job: every shard is read once for all of them."""
        plans = [(p, compile_path(p)) for p in paths]
        if self.spine is not None:
            following = [p for p, a in plans if any(s.axis == FOLLOWING for s in a.steps)]
            plans = [(p, a) for p, a in plans if p not in following]
        else:
            following = []
        entries = [self.spine_plan(a).entry if self.spine else {} for _, a in plans]
        base = [self.spine_plan(a).selected_count() if self.spine else 0 for _, a in plans]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros(len(plans), np.int64)
            for row in _shards(batches):
                g = load_shard(row)
                for k, (_, a) in enumerate(plans):
                    q = entries[k].get(row["section"], a.initial)
                    if q != a.universal:
                        total[k] += int(Run(g, a).eager_count(q)[0].sum())
            yield _batch([(k, int(n)) for k, n in enumerate(total)], ["k", "n"], [pa.int32(), pa.int64()])

        sums = self.shards.select(*CORE).mapInArrow(run, "k int, n long").groupBy("k").agg(F.sum("n").alias("n"))
        names = self.spark.createDataFrame([(k, p, b) for k, ((p, _), b) in enumerate(zip(plans, base, strict=True))], "k int, path string, base long")
        out = names.join(sums, "k", "left").select("path", (F.coalesce("n", F.lit(0)) + F.col("base")).cast("long").alias("n"))
        for p in following:
            out = out.unionAll(self.count(p).select(F.lit(p).alias("path"), "n"))
        return out

    def resident(self, max_bytes: int = 64 << 20) -> Resident | None:
        """The grammars in the driver's memory, for many small questions to a small index; None if they take more than ``max_bytes``.

        The size is summed up on the executors first; texts and tables stay where they are."""
        size = self.shards.agg(F.sum(8 * F.size("rules") + 4 * F.size("start") + 12 * F.size("doc_ids")).alias("b")).first()["b"] or 0
        if size > max_bytes:
            return None
        rows = [r.asDict() for r in self.shards.select(*CORE).toLocalIterator()]
        return Resident(self, [(r["section"], r["shard_no"], load_shard(r)) for r in sorted(rows, key=lambda r: (r["section"], r["shard_no"]))])

    def label_count(self, label: str, within: tuple[int, int, int] | None = None) -> DataFrame:
        """(n) of the elements with a label, of all documents or of a subtree: document, structure number and size."""
        if within is None:
            return self.count(f"//{label}")
        doc, node, size = within
        hits = self._clipped(doc, node, node + size).materialize(f"//{label}")
        return hits.where((F.col("doc_id") == doc) & F.col("node").between(node, node + size - 1)).agg(F.count("*").alias("n"))

    def _clipped(self, doc: int, first: int, end: int) -> TreeIndex:
        """This index with only those shards that hold structure numbers from ``first`` to ``end`` of a document; numbers stay what they were."""
        if self.spine is None:
            return TreeIndex(self.spark, self.shards.where(F.array_contains("doc_ids", F.lit(doc).cast("long"))), self.name, None, self.path)
        offsets = self.offsets(self.spine_plan(compile_path("/*")))
        live = offsets.join(self.shards.select("section", "shard_no", "n_node"), ["section", "shard_no"]).where((F.col("n0") < end) & (F.col("n0") + F.col("n_node") > first))
        out = TreeIndex(self.spark, self.shards.join(live.select("section", "shard_no"), ["section", "shard_no"], "left_semi"), self.name, self.spine, self.path)
        # Places and totals are those of the whole document.
        out._totals, out._n_shards = self.totals(), self._n_shards
        out.offsets = self.offsets
        return out

    def selectivity(self, path: str) -> DataFrame:
        """(n, elements, fraction): the exact share of elements that a path selects."""
        total = self.shards.agg(F.sum("n_elem").alias("e")).select((F.col("e") + (self.spine_size() if self.spine else 0)).alias("elements"))
        return self.count(path).crossJoin(total).select("n", "elements", (F.col("n") / F.col("elements")).alias("fraction"))  # one row on either side

    def spine_size(self) -> int:
        return sum(1 for _ in _spine_nodes(self.spine)) if self.spine else 0

    # Node numbers

    def totals(self) -> dict[int, tuple[int, int, int]]:
        """Elements, nodes and texts of each section: a handful of rows, summed up once."""
        if self._totals is None:
            sums = self.shards.groupBy("section").agg(F.sum("n_elem").alias("e"), F.sum("n_node").alias("n"), F.sum("n_text").alias("t"), F.count("*").alias("w")).collect()
            self._totals = {r["section"]: (int(r["e"]), int(r["n"]), int(r["t"])) for r in sums}
            self._n_shards = sum(r["w"] for r in sums)
        return self._totals

    def offsets(self, plan: SpinePlan) -> DataFrame:
        """(section, shard_no, e0, n0, t0): elements, nodes and texts of the giant document before each shard."""
        bases = plan.bases(self.totals())
        at = lambda k: F.coalesce(*[F.when(F.col("section") == s, F.lit(b[k])) for s, b in bases.items()], F.lit(0)).cast("long")
        sums = before(self.shards.select("section", "shard_no", "n_elem", "n_node", "n_text"), "section", "shard_no", {"e": "n_elem", "n": "n_node", "t": "n_text"})
        return sums.select("section", "shard_no", (F.col("e") + at(0)).alias("e0"), (F.col("n") + at(1)).alias("n0"), (F.col("t") + at(2)).alias("t0"))

    def _placed(self, src: DataFrame, a: Automaton | None, plan: SpinePlan) -> tuple[DataFrame, dict | None]:
        """Where the shards of a giant document stand and in which state they are entered: a short table that is shipped
        with the task up to ``SHIPPED_SHARDS`` shards, else columns that are joined to ``src``."""
        self.totals()
        following = a is not None and any(s.axis == FOLLOWING for s in a.steps)
        if following:
            states = compose(self.behaviours("".join(_show(s) for s in a.steps), prune=False), plan).select("section", "shard_no", "q_in")
        elif a is not None:
            entry = F.coalesce(*[F.when(F.col("section") == s, F.lit(q)) for s, q in plan.entry.items()]).cast("int")
            states = self.shards.select("section", "shard_no", entry.alias("q_in"))
        else:
            states = self.shards.select("section", "shard_no", F.lit(None).cast("int").alias("q_in"))
        if self._n_shards > SHIPPED_SHARDS:
            return src.join(self.offsets(plan).join(states, ["section", "shard_no"]), ["section", "shard_no"]), None
        if self._places is None:
            self._places = {(r["section"], r["shard_no"]): (r["e0"], r["n0"], r["t0"]) for r in self.offsets(plan).collect()}
        q = {(r["section"], r["shard_no"]): r["q_in"] for r in states.collect()} if following else {k: plan.entry.get(k[0]) for k in self._places}
        if a is not None:
            live = sorted({k[0] for k in self._places if q.get(k) != a.universal})
            src = src.where(F.col("section").isin(live))
        return src, {k: (q.get(k), *v) for k, v in self._places.items()}

    def materialize(self, path: str, limit: int | None = None, mode: str = "eager", jump: bool = True, start_skip: bool = True) -> DataFrame:
        """(doc_id, node, pre) of the selected nodes: structure and element numbers from 0 in document order; pre is null for texts and attributes.

        The lazy mode works out only the rules and states that the walk meets, and ``jump`` lets it pass over those without relevant labels."""
        a = compile_path(path)
        element = a.steps[-1].kind == "element"
        src, places = self._pruned(a).select(*CORE), None
        plan = self.spine_plan(a) if self.spine is not None else None
        if plan is not None:
            src, places = self._placed(src, a, plan)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _shards(batches):
                q, e0, n0, _ = _place(row, places)
                if q is not None and q == a.universal:
                    continue
                got, _ = Chunkwise(Run(load_shard(row), a, jump), start_skip=start_skip, lazy=mode == "lazy").materialize(q, limit)
                for d, pos in zip(row["doc_ids"].tolist(), got, strict=True):
                    n = pos.shape[1]
                    pre = pa.array(pos[0] + e0, pa.int64()) if element else pa.nulls(n, pa.int64())
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(n, d, np.int64)), pa.array(pos[1] + n0, pa.int64()), pre], names=["doc_id", "node", "pre"])

        schema = "doc_id long, node long, pre long"
        out = src.mapInArrow(run, schema)
        if plan is not None:
            top = [(0, n, e) for e, n in plan.selected_numbers(self.totals())]
            if top:
                out = out.unionAll(self.spark.createDataFrame(top, schema))
        return out.orderBy("doc_id", "node").limit(limit) if limit is not None else out

    # Serialization

    def serialize(self, path: str, copy: bool = True, start_skip: bool = True) -> DataFrame:
        """(doc_id, pre, piece_no, xml) of the selected subtrees; a result that spans shards comes in ordered pieces."""
        a = compile_path(path)
        src, places = self._pruned(a).select(*CORE, "doc_texts", "texts"), None
        plan = self.spine_plan(a) if self.spine is not None else None
        if plan is not None:
            src, places = self._placed(src, a, plan)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _shards(batches):
                q, e0, _, _ = _place(row, places)
                if q is not None and q == a.universal:
                    continue
                g = load_shard(row)
                got, _ = Chunkwise(Run(g, a), copy, start_skip).serialize(row["texts"], row["doc_texts"], q)
                out, size, show = [], 0, Renderer(g.names, row["texts"])
                for d, (tags, res), t0 in zip(row["doc_ids"].tolist(), got, row["doc_texts"].tolist(), strict=True):
                    if not res.shape[1]:
                        continue
                    ends = subtree_ends(tags, res[0]).tolist()
                    for b, e, pre, t in zip(res[0].tolist(), ends, res[1].tolist(), res[3].tolist(), strict=True):
                        xml = show(tags, b, e, t0 + t)
                        out.append((d, pre + e0, 0, xml))
                        size += len(xml)
                        if size > 4 << 20:
                            yield _batch(out, ["doc_id", "pre", "piece_no", "xml"], [pa.int64(), pa.int64(), pa.int64(), pa.string()])
                            out, size = [], 0
                yield _batch(out, ["doc_id", "pre", "piece_no", "xml"], [pa.int64(), pa.int64(), pa.int64(), pa.string()])

        schema = "doc_id long, pre long, piece_no long, xml string"
        out = src.mapInArrow(run, schema)
        if plan is None:
            return out
        pieces = plan.pieces(self.totals())
        if pieces:
            whole = self.render_shards()
            items = self.spark.createDataFrame(pieces, "pre long, item long, section int, literal string")
            literal = items.where("section is null").select(F.lit(0).cast("long").alias("doc_id"), "pre", F.shiftleft("item", 32).alias("piece_no"), F.col("literal").alias("xml"))
            inner = items.where("section is not null").select("pre", "item", "section").join(whole, "section").select(F.lit(0).cast("long").alias("doc_id"), "pre", (F.shiftleft("item", 32) + F.col("shard_no") + 1).alias("piece_no"), "xml")
            out = out.unionByName(literal).unionByName(inner)
        return out

    def render_shards(self) -> DataFrame:
        """(section, shard_no, xml): the whole text of each shard (decompression)."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _shards(batches):
                g = load_shard(row)
                tags = g.expand()
                tags = tags[tags != -2] if g.open_end else tags
                yield _batch([(row["section"], row["shard_no"], render(tags.tolist(), g.names, row["texts"], 0))], ["section", "shard_no", "xml"], [pa.int32(), pa.int64(), pa.string()])

        return self.shards.select(*CORE, "texts").mapInArrow(run, "section int, shard_no long, xml string")

    def documents(self) -> DataFrame:
        """(doc_id, xml): every document written anew from the index; well-formed whatever the source was."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _shards(batches):
                g = load_shard(row)
                stream, at, out = g.expand(), 0, []
                for d, n, t in zip(row["doc_ids"].tolist(), g.totals("node").tolist(), row["doc_texts"].tolist(), strict=True):
                    out.append((d, render(stream[at : at + 2 * n].tolist(), g.names, row["texts"], t)))
                    at += 2 * n + 1
                yield _batch(out, ["doc_id", "xml"], [pa.int64(), pa.string()])

        return self.shards.select(*CORE, "texts", "doc_texts").mapInArrow(run, "doc_id long, xml string")

    # Decompression to nodes

    def nodes(self) -> DataFrame:
        """(section, shard_no, doc_id, node, label, kind, pre, size, element_size, parent, level, text_no, path) of every structure node.

        For a giant document numbers are those of the whole document; roots of a run have the spine element as parent."""
        plan = SpinePlan(self.spine, None) if self.spine else None
        paths = plan.section_paths(self.totals()) if plan else {}
        src, places = self.shards.select(*CORE), None
        if plan is not None:
            src, places = self._placed(src, None, plan)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _shards(batches):
                g = load_shard(row)
                stream, at = g.expand(), 0
                names = np.array([n for _, n in g.names], object)
                top, depth, above = paths.get(row["section"], ("", 0, -1))
                _, e0, n0, t0 = _place(row, places)
                for d, n in zip(row["doc_ids"].tolist(), g.totals("node").tolist(), strict=True):
                    t = node_table(stream[at : at + 2 * n], [k for k, _ in g.names])
                    at += 2 * n + 1
                    known: dict[tuple[str, int], str] = {}
                    path: list[str] = []
                    for p, lab in zip(t["parent"].tolist(), t["label"].tolist(), strict=True):
                        key = (path[p] if p >= 0 else top, lab)
                        got = known.get(key)
                        if got is None:
                            got = known[key] = f"{key[0]}/{names[lab]}"
                        path.append(got)
                    pre, text = t["pre"], t["text_no"]
                    cols = [
                        pa.array(np.full(n, row["section"], np.int32)), pa.array(np.full(n, row["shard_no"], np.int64)), pa.array(np.full(n, d, np.int64)), pa.array(np.arange(n) + n0), pa.array(names[t["label"]].tolist() if n else [], pa.string()),
                        pa.array(t["kind"].astype(np.int32)), pa.array(pre + e0, pa.int64(), mask=pre < 0), pa.array(t["size"], pa.int64()), pa.array(t["element_size"], pa.int64()),
                        pa.array(np.where(t["parent"] >= 0, t["parent"] + n0, above), pa.int64(), mask=(t["parent"] < 0) & (above < 0)), pa.array(t["level"] + depth, pa.int64()), pa.array(text + t0, pa.int64(), mask=text < 0), pa.array(path, pa.string()),
                    ]
                    yield pa.RecordBatch.from_arrays(cols, names=["section", "shard_no", "doc_id", "node", "label", "kind", "pre", "size", "element_size", "parent", "level", "text_no", "path"])

        schema = "section int, shard_no long, doc_id long, node long, label string, kind int, pre long, size long, element_size long, parent long, level long, text_no long, path string"
        out = src.mapInArrow(run, schema)
        return out if plan is None else out.unionAll(self.spark.createDataFrame(plan.rows(self.totals()), schema))

    def texts(self) -> DataFrame:
        """(doc_id, text_no, value) of all text and attribute values of documents (or of the giant document)."""
        if self.spine is None:
            ends = F.concat(F.expr("slice(doc_texts, 2, greatest(size(doc_texts) - 1, 0))"), F.array(F.size("texts")))
            per = self.shards.select("texts", F.explode(F.arrays_zip("doc_ids", F.col("doc_texts").alias("t0"), ends.alias("t1"))).alias("d"))
            per = per.select(F.col("d.doc_ids").alias("doc_id"), F.slice("texts", F.col("d.t0") + 1, F.col("d.t1") - F.col("d.t0")).alias("own"))
            return per.select("doc_id", F.posexplode("own").alias("text_no", "value")).select("doc_id", F.col("text_no").cast("long").alias("text_no"), "value")
        off = self.offsets(SpinePlan(self.spine, None)).select("section", "shard_no", "t0")
        return self.shards.select("section", "shard_no", "texts").join(off, ["section", "shard_no"]).select(F.lit(0).cast("long").alias("doc_id"), F.posexplode("texts").alias("k", "value"), "t0").select("doc_id", (F.col("t0") + F.col("k")).alias("text_no"), "value")

    def get_text(self, doc_id: int, text_no: int) -> DataFrame:
        """The value with a text number in one document."""
        return self.texts().where((F.col("doc_id") == doc_id) & (F.col("text_no") == text_no))

    # Node-wise view

    def _cursors(self, fn, schema: str, columns: list[str] | None = None) -> DataFrame:
        names, types = [c.split(" ")[0] for c in schema.split(", ")], [{"long": pa.int64(), "string": pa.string(), "int": pa.int32()}[c.split(" ")[1]] for c in schema.split(", ")]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _shards(batches):
                yield _batch(list(fn(row, load_shard(row))), names, types)

        return self.shards.select(*CORE, *(columns or [])).mapInArrow(run, schema)

    def traverse(self, order: str = "dflr", mode: str = "rec", pool: bool = True) -> DataFrame:
        """(doc_id, visited, checksum) of full traversals by the cursor; runs of a giant document count as documents of their shard."""

        def fn(row, g):
            c = Cursor(g, pool)
            for d, root in zip(row["doc_ids"].tolist(), c.roots(), strict=True):
                yield (d, *c.traverse(root, order, mode))

        return self._cursors(fn, "doc_id long, visited long, checksum long")

    def generic_count(self, path: str, use_tagged: bool = True) -> DataFrame:
        """(doc_id, n) by the plain evaluator on the node-wise interface; documents only."""
        from treegrammar.views.generic import count

        def fn(row, g):
            c = Cursor(g)
            for d, root in zip(row["doc_ids"].tolist(), c.roots(), strict=True):
                yield d, count(c, root, path, use_tagged)

        return self._cursors(fn, "doc_id long, n long")

    def tagged(self, label: str, pre: int = 0, kind: str = "desc") -> DataFrame:
        """(doc_id, found) whether, from the element ``pre`` of each document, a descendant or following node has the label."""

        def fn(row, g):
            c = Cursor(g)
            number = {n: k for k, n in enumerate(g.names)}.get((0, label))
            for k, d in enumerate(row["doc_ids"].tolist()):
                node = c.locate(k, pre)
                jump = c.tagged_desc if kind == "desc" else c.tagged_foll
                yield d, int(node is not None and number is not None and jump(node, number) is not None)

        return self._cursors(fn, "doc_id long, found long")

    def locate(self, doc_id: int, pre: int) -> DataFrame:
        """(doc_id, label) of an element by its number."""

        def fn(row, g):
            c = Cursor(g)
            for k, d in enumerate(row["doc_ids"].tolist()):
                if d == doc_id and (node := c.locate(k, pre)) is not None:
                    yield d, g.names[c.label(node)][1]

        return self._cursors(fn, "doc_id long, label string")

    # Measures

    def stats(self) -> DataFrame:
        """Shape and size of every shard: edges, rules, start, depth, ranks, and the modelled bytes of each component."""
        from treegrammar.measure import shard_stats

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _shards(batches):
                s = shard_stats(load_shard(row))
                yield _batch([(row["carrier"], row["section"], row["shard_no"], *s.values())], ["carrier", "section", "shard_no", *s], [pa.string(), pa.int32(), pa.int64(), *[pa.float64() if isinstance(v, float) else pa.int64() for v in s.values()]])

        from treegrammar.measure import STATS_SCHEMA

        return self.shards.select(*CORE).mapInArrow(run, "carrier string, section int, shard_no long, " + STATS_SCHEMA)

    def actual_bytes(self) -> DataFrame:
        """Bytes of the stored arrays of each component, and of the texts, next to the model of ``stats``."""
        size = lambda c, w: F.sum(F.coalesce(F.size(c), F.lit(0)) * w).cast("long")
        return self.shards.agg(
            size("rules", 8).alias("rules"), size("start", 4).alias("start"), size("start_close", 4).alias("shape_explicit"), F.sum(F.octet_length("start_bp")).alias("shape_parentheses"), size("jump", 8).alias("jump"),
            size("elem_chunks", 4).alias("element_map"), size("text_chunks", 4).alias("text_map"), size("skip_elem", 4).alias("skip"), F.sum("text_bytes").alias("texts"),
        )

    def build_report(self) -> DataFrame:
        """Seconds of each stage over all shards, the slowest shard, and the largest worker."""
        return self.shards.agg(*[F.sum(c).alias(c) for c in ("t_structure", "t_compress", "t_tables")], F.max(F.col("t_structure") + F.col("t_compress") + F.col("t_tables")).alias("slowest_shard"), F.max("peak_mb").alias("peak_mb"))

    def normal_form_shapes(self) -> DataFrame:
        """What the binary normal form does to each shard's grammar: rules, edges, depth and rank before and after."""
        from treegrammar.grammar.normal_form import shapes

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _shards(batches):
                s = shapes(load_shard(row))
                yield _batch([(row["section"], row["shard_no"], *s.values())], ["section", "shard_no", *s], [pa.int32(), pa.int64(), *[pa.float64() if k == "growth_percent" else pa.int64() for k in s]])

        schema = "section int, shard_no long, start long, rules_before long, rules_after long, depth_before long, depth_after long, edges_before long, edges_after long, growth_percent double, rank_before long, rank_after long"
        return self.shards.select(*CORE).mapInArrow(run, schema)

    def cached(self) -> TreeIndex:
        self.shards = written(self.spark, self.shards, "index-copy")
        return self


class Resident:
    """A small index in memory; answers counts without a job, by the same evaluator."""

    def __init__(self, index: TreeIndex, grammars: list[tuple[int, int, Grammar]]):
        self.spine = index.spine
        self.grammars = grammars
        self._label_sets = [frozenset(n for _, n in g.names) for _, _, g in self.grammars]

    def count(self, path: str) -> int:
        a = compile_path(path)
        last = a.steps[-1].name
        plan = SpinePlan(self.spine, a) if self.spine else None
        following = plan is not None and any(s.axis == FOLLOWING for s in a.steps)
        total, states = (plan.selected_count() if plan else 0), dict(plan.entry) if plan else {}
        for (section, _, g), labels in zip(self.grammars, self._label_sets, strict=True):
            q = states.get(section, a.initial)
            if q == a.universal or not following and last is not None and last not in labels:
                continue
            run = Run(g, a)
            n, out = run.eager_count(q)
            total += int(n.sum())
            if following:
                states[section] = out
        return total


ARROW_SCHEMA = pa.schema([
    (n, {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "boolean": pa.bool_(), "binary": pa.binary(), "double": pa.float64(), "array<int>": pa.list_(pa.int32()), "array<long>": pa.list_(pa.int64()), "array<string>": pa.list_(pa.string())}[t])
    for n, t in (c.strip().split(" ") for c in SHARD_SCHEMA.split(","))
])


def _spine_nodes(spine: Spine) -> Iterator[Spine]:
    yield spine
    for c in spine.children:
        yield from _spine_nodes(c)


def _spine_json(s: Spine | None):
    return None if s is None else {"name": s.name, "section": s.section, "children": [_spine_json(c) for c in s.children]}


def _spine_of(d) -> Spine | None:
    return None if d is None else Spine(d["name"], [_spine_of(c) for c in d["children"]], d["section"])


def _show(step) -> str:
    """A step as text; attribute steps come in twos, of which the first shows the axis."""
    sep = {"child": "/", "descendant": "//", "following-sibling": "/following-sibling::"}[step.axis]
    if step.kind == "attrs":
        return sep
    if step.kind == "attr":
        return step.name or "@*"
    return sep + ("text()" if step.kind == "text" else step.name or "*")


class SpinePlan:
    """What an automaton does on the spine: selected spine elements and the entry state of each section."""

    def __init__(self, spine: Spine, automaton: Automaton | None):
        self.spine, self.a = spine, automaton
        self.entry: dict[int, int] = {}
        self.selected: list[Spine] = []
        if automaton is not None:
            self._walk([spine], automaton.initial)

    def _walk(self, nodes: list[Spine], q: int) -> None:
        a = self.a
        for s in nodes:
            c = int(a.classify([(0, s.name)])[0])
            if a.selects[q, c]:
                self.selected.append(s)
            down, right = int(a.to_down[q, c]), int(a.to_right[q, c])
            if s.section is not None:
                self.entry[s.section] = down
            self._walk(s.children, down)
            q = right

    def selected_count(self) -> int:
        return len(self.selected)

    def _numbers(self, totals: dict[int, tuple[int, int, int]]) -> dict[int, tuple[tuple[int, int, int], tuple[int, int, int]]]:
        """id(spine element) -> counts (elements, nodes, texts) before it and after its subtree."""
        out: dict[int, tuple] = {}

        def walk(s: Spine, at: tuple[int, int, int]) -> tuple[int, int, int]:
            now = (at[0] + 1, at[1] + 1, at[2])
            if s.section is not None:
                t = totals.get(s.section, (0, 0, 0))
                now = (now[0] + t[0], now[1] + t[1], now[2] + t[2])
            for c in s.children:
                now = walk(c, now)
            out[id(s)] = (at, now)
            return now

        walk(self.spine, (0, 0, 0))
        return out

    def bases(self, totals) -> dict[int, tuple[int, int, int]]:
        n = self._numbers(totals)
        return {s.section: (n[id(s)][0][0] + 1, n[id(s)][0][1] + 1, n[id(s)][0][2]) for s in _spine_nodes(self.spine) if s.section is not None}

    def selected_numbers(self, totals) -> list[tuple[int, int]]:
        n = self._numbers(totals)
        return [n[id(s)][0][:2] for s in self.selected]

    def section_paths(self, totals=None) -> dict[int, tuple[str, int, int]]:
        """section -> path of its spine element, elements above its records, and its structure number."""
        n = self._numbers(totals or {})
        out = {}

        def walk(s: Spine, path: str, depth: int) -> None:
            path = f"{path}/{s.name}"
            if s.section is not None:
                out[s.section] = (path, depth + 1, n[id(s)][0][1])
            for c in s.children:
                walk(c, path, depth + 1)

        walk(self.spine, "", 0)
        return out

    def rows(self, totals) -> list[tuple]:
        """The spine as rows of the node table; they belong to section and shard -1."""
        n, out = self._numbers(totals), []

        def walk(s: Spine, path: str, depth: int, parent: int | None) -> None:
            before, after = n[id(s)]
            path = f"{path}/{s.name}"
            out.append((-1, -1, 0, before[1], s.name, 0, before[0], after[1] - before[1], after[0] - before[0], parent, depth, None, path))
            for c in s.children:
                walk(c, path, depth + 1, before[1])

        walk(self.spine, "", 0, None)
        return out

    def pieces(self, totals) -> list[tuple[int, int, int | None, str | None]]:
        """(pre, item, section, literal): each selected spine element as literals and sections in order."""
        n, out = self._numbers(totals), []
        for top in self.selected:
            items: list[tuple[int | None, str | None]] = []

            def walk(s: Spine, items=items) -> None:
                items.append((None, f"<{s.name}>"))
                if s.section is not None:
                    items.append((s.section, None))
                for c in s.children:
                    walk(c)
                items.append((None, f"</{s.name}>"))

            walk(top)
            out += [(n[id(top)][0][0], k, sec, lit) for k, (sec, lit) in enumerate(items)]
        return out


#: Shards of a section whose behaviours one task composes.
COMPOSE_GROUP = 1000


def compose(rows: DataFrame, plan: SpinePlan) -> DataFrame:
    """Pick, for every shard of a giant document, the behaviour row of the state in which the shard is really entered.

    Composition is associative: groups of consecutive shards are composed into one map from state to state, the short list of groups is
    folded on the driver, and each group then replays its shards from its own entry state."""
    grouped = rows.withColumn("grp", F.floor(F.col("shard_no") / COMPOSE_GROUP))

    def maps(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        t = table.sort_by([("shard_no", "ascending"), ("q_in", "ascending")]).to_pylist()
        now: dict[int, int] = {}
        by: dict[int, dict[int, int]] = {}
        for r in t:
            by.setdefault(r["shard_no"], {})[r["q_in"]] = r["q_out"]
        for no in sorted(by):
            now = {q: by[no][p] for q, p in (now or {q: q for q in by[no]}).items()}
        return pa.Table.from_pylist([{"section": key[0].as_py(), "grp": key[1].as_py(), "q": q, "out": o} for q, o in now.items()], schema=pa.schema([("section", pa.int32()), ("grp", pa.int64()), ("q", pa.int32()), ("out", pa.int32())]))

    small = grouped.select("section", "grp", "shard_no", "q_in", "q_out").groupBy("section", "grp").applyInArrow(maps, "section int, grp long, q int, out int")
    steps: dict[int, dict[int, dict[int, int]]] = {}
    for r in small.toLocalIterator():  # a thousandth of the shards, times the states
        steps.setdefault(r["section"], {}).setdefault(r["grp"], {})[r["q"]] = r["out"]
    entry: dict[tuple[int, int], int] = {}
    for section, groups in steps.items():
        q = plan.entry[section]
        for grp in sorted(groups):
            entry[section, grp] = q
            q = groups[grp][q]

    def replay(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        by: dict[int, dict[int, dict]] = {}
        for r in table.to_pylist():
            by.setdefault(r["shard_no"], {})[r["q_in"]] = r
        q, out = entry[key[0].as_py(), key[1].as_py()], []
        for no in sorted(by):
            r = by[no][q]
            out.append({k: r[k] for k in ("section", "shard_no", "q_in", "n", "q_out")})
            q = r["q_out"]
        return pa.Table.from_pylist(out, schema=pa.schema([("section", pa.int32()), ("shard_no", pa.int64()), ("q_in", pa.int32()), ("n", pa.int64()), ("q_out", pa.int32())]))

    return grouped.select("section", "grp", "shard_no", "q_in", "n", "q_out").groupBy("section", "grp").applyInArrow(replay, "section int, shard_no long, q_in int, n long, q_out int")


__all__ = ["CORE", "SHARD_NODES", "SHARD_SCHEMA", "SpinePlan", "TreeIndex", "assign_shards", "compose", "load_shard", "parse_path", "shard_row", "start_parentheses"]
