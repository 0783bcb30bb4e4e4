"""Sharding by k-d tree partitioning, in DataFrame operations only.

Equal texts form a group, which is never cut. A group has a weight (its bytes) and metadata coordinates in [0, 1): size,
language, source, and position in the table. Starting from one node, all nodes of a level are split together: each along
the dimension in which it is widest, at the weighted median of its groups. The median is found by radix selection over
order keys (the coordinate, then a hash of the text for ties): a round sums the weights of at most 2**``RADIX`` bins a
node, finds the bin on the median in a window over these bins, and stops when that bin is light enough. The tree itself is a
table with a row for each node, so neither the number of shards nor of bins bears on the driver. With a number of shards
that is no power of two the weights are cut in proportion.

Slots: rows of a shard are numbered within hash chunks whose number grows with the table, and the chunk counts are
summed up, so no task ever orders a whole shard. The shards of hot groups are broadcast to their rows (a bounded number of
groups), so copies of one text are not gathered in one task.

Defined results: null texts have no bytes and size 1; null metadata has coordinate 0; equal texts share a shard;
repeated rows get slots of their own; an empty table gives no rows; columns besides those named are ignored. Sizes are
near equal unless a single group outweighs a shard, since equal texts stay together.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from treegrammar.llm.skew import join_entries
from treegrammar.shared import written

RADIX, ROUNDS, KEY_BITS = 14, 4, 56
#: Share of a node's weight by which a cut may miss the median.
TOLERANCE = 1e-4
CHUNK_ROWS = 20_000
DIMENSIONS = ("x_size", "x_lang", "x_source", "x_place")


def _fraction(value: Column) -> Column:
    return F.coalesce(F.pmod(F.xxhash64(value), F.lit(1 << 20)) / F.lit(float(1 << 20)), F.lit(0.0))


def group_table(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rows (doc_id, size, text_crc32, digest) and groups (digest, weight, coordinates)."""
    text = F.col("text").cast("string")
    has = lambda c: F.col(c) if c in docs.columns else F.lit(None)
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long").alias("size"),
        F.crc32(F.coalesce(text, F.lit("")).cast("binary")).alias("text_crc32"), F.unhex(F.sha2(F.coalesce(text, F.lit("")).cast("binary"), 256)).alias("digest"),
        text.isNull().alias("none"), has("lang").cast("string").alias("lang"), has("source").cast("string").alias("source"),
    )
    return rows


def grouped(rows: DataFrame) -> DataFrame:
    ends = rows.agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).first()
    lo, hi = ends["lo"] or 0, (ends["hi"] or 0) + 1
    one = rows.groupBy("digest", "none").agg(F.sum("size").alias("weight"), F.count("*").alias("copies"), F.min(F.struct("doc_id", "size", "lang", "source")).alias("m"))
    place = F.coalesce((F.col("m.doc_id") - lo) / F.lit(float(max(1, hi - lo))), F.lit(0.0))
    return one.select(
        "digest", "none", "weight", "copies", F.least(F.log2(F.col("m.size").cast("double")) / 40, F.lit(0.999999)).alias("x_size"), _fraction(F.col("m.lang")).alias("x_lang"),
        _fraction(F.col("m.source")).alias("x_source"), F.least(place, F.lit(0.999999)).alias("x_place"), F.xxhash64("digest", "none").alias("tie"),
    )


def _key(dim: Column) -> Column:
    """The order key along a dimension: 24 bits of coordinate, then 32 bits of hash."""
    x = F.coalesce(*[F.when(dim == k, F.col(c)) for k, c in enumerate(DIMENSIONS)])
    return F.shiftleft(F.floor(x * float(1 << 24)).cast("long"), 32).bitwiseOR(F.col("tie").bitwiseAND(0xFFFFFFFF))


def split_level(spark: SparkSession, groups: DataFrame, nodes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Split every node (node, first, shards) that has more than one shard; the groups' new nodes and the new tree level."""
    spread = [(F.max(c) - F.min(c)).alias(f"s{k}") for k, c in enumerate(DIMENSIONS)]
    widest = F.greatest(*[F.col(f"s{k}") for k in range(len(DIMENSIONS))])
    dim = F.coalesce(*[F.when(F.col(f"s{k}") == widest, k) for k in range(len(DIMENSIONS))])
    live = groups.join(nodes.where("shards > 1"), "node").groupBy("node", "first", "shards").agg(F.sum("weight").alias("total"), *spread)
    want = F.col("total") * F.floor(F.col("shards") / 2) / F.col("shards")
    cuts = live.select("node", "first", "shards", "total", dim.alias("dim"), want.alias("want"), F.lit(0).cast("long").alias("prefix"), F.lit(0).cast("long").alias("below"), F.lit(None).cast("long").alias("cut"))
    cuts = written(spark, cuts, "kd-cuts")
    shift = KEY_BITS
    for _ in range(ROUNDS):
        open_ = cuts.where("cut is null")
        if open_.isEmpty():
            break
        at = groups.join(open_.select("node", "dim", "prefix"), "node").withColumn("key", _key(F.col("dim"))).where(F.shiftright("key", shift) == F.col("prefix"))
        shift -= RADIX
        bins = at.groupBy("node", F.shiftright("key", shift).alias("bin")).agg(F.sum("weight").alias("w"))
        upto = F.sum("w").over(Window.partitionBy("node").orderBy("bin"))  # at most 2**RADIX bins a node
        hit = bins.withColumn("upto", upto).join(open_, "node").where(F.col("below") + F.col("upto") >= F.col("want")).groupBy("node").agg(F.min(F.struct("bin", "w", "upto")).alias("b"))
        start = F.col("below") + F.col("b.upto") - F.col("b.w")
        short, over = F.col("want") - start, start + F.col("b.w") - F.col("want")
        # The cut goes before or after the bin, whichever misses less; a heavy bin is opened further.
        done = (F.least(short, over) <= TOLERANCE * F.col("total")) | F.lit(shift <= 0)
        place = F.shiftleft(F.col("b.bin") + F.when(short <= over, 0).otherwise(1), shift)
        moved = open_.join(hit, "node").select("node", "first", "shards", "total", "dim", "want", F.col("b.bin").alias("prefix"), start.alias("below"), F.when(done, place).alias("cut"))
        cuts = written(spark, cuts.where("cut is not null").unionByName(moved), "kd-cuts")
    cut = cuts.where("cut is not null").select("node", "dim", "cut", F.floor(F.col("shards") / 2).cast("int").alias("left"))
    step = F.when(F.col("cut").isNotNull(), (_key(F.col("dim")) >= F.col("cut")).cast("int")).otherwise(0)
    groups = groups.join(cut.drop("left"), "node", "left").withColumn("node", F.col("node") * 2 + step).drop("dim", "cut")
    below = nodes.join(cut.select("node", "left"), "node", "left")
    part = F.explode(F.when(F.col("left").isNull(), F.array(F.struct(F.lit(0).alias("side"), F.col("first").alias("f"), F.lit(1).alias("n")))).otherwise(
        F.array(F.struct(F.lit(0).alias("side"), F.col("first").alias("f"), F.col("left").alias("n")), F.struct(F.lit(1).alias("side"), (F.col("first") + F.col("left")).alias("f"), (F.col("shards") - F.col("left")).alias("n")))))
    nodes = below.withColumn("p", part).select((F.col("node") * 2 + F.col("p.side")).alias("node"), F.col("p.f").cast("int").alias("first"), F.col("p.n").cast("int").alias("shards"))
    return written(spark, groups, "kd-groups"), written(spark, nodes, "kd-nodes")


def place_groups(spark: SparkSession, groups: DataFrame, shards: int) -> DataFrame:
    """digest, none, copies, shard of every group. A node that cannot be split (it has no groups) keeps its first shard."""
    groups = groups.withColumn("node", F.lit(1).cast("long"))
    nodes = spark.range(1).select(F.lit(1).cast("long").alias("node"), F.lit(0).alias("first"), F.lit(shards).alias("shards"))
    for _ in range((shards - 1).bit_length()):
        groups, nodes = split_level(spark, groups, nodes)
    return groups.join(nodes.select("node", F.col("first").alias("shard")), "node").select("digest", "none", "copies", "shard")


def shard_documents(spark: SparkSession, docs: DataFrame, shards: int | None = 8, target_bytes: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of every row; the number of shards, or bytes a shard aims at."""
    rows = written(spark, group_table(docs), "shard-rows")
    groups = written(spark, grouped(rows), "shard-groups")
    total = groups.agg(F.sum("weight"), F.count("*")).first()
    if target_bytes:
        shards = max(1, -(-int(total[0] or 0) // target_bytes))
    placed = written(spark, place_groups(spark, groups, shards), "shard-of-group")
    total_rows = rows.count()
    chunks = max(1, -(-total_rows // CHUNK_ROWS))
    chunk = F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(chunks)).cast("int")
    out = written(spark, join_entries(rows, placed, ["digest", "none"], "copies", total_rows).select("doc_id", "size", "text_crc32", "shard", chunk.alias("chunk")), "placed")
    before = Window.partitionBy("shard").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    starts = out.groupBy("shard", "chunk").agg(F.count("*").alias("n")).select("shard", "chunk", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    within = Window.partitionBy("shard", "chunk").orderBy("doc_id", "text_crc32")
    numbered = out.withColumn("k", F.row_number().over(within) - 1).join(starts, ["shard", "chunk"])
    return numbered.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("start") + F.col("k")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
