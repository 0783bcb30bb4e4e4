"""The rule-wise run as joins, for indexes whose documents are single symbols: no kernel evaluates the automaton.

Behaviours (symbol, state) -> (selected, states at the holes) start with the labels; level by level the rules join the
behaviour of their outer part in every state and that of their inner part in the state at the hole.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treegrammar.functions.tree_functions import rule_hole, rule_inner, rule_outer
from treegrammar.operators.index import CORE, TreeIndex, _shards, load_shard
from treegrammar.shared import written
from treegrammar.xpath.automaton import compile_path


def rule_levels(index: TreeIndex) -> DataFrame:
    """(section, shard_no, k, lvl) of every rule."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _shards(batches):
            g = load_shard(row)
            for lvl, rules in enumerate(g.levels(), 1):
                n = len(rules)
                yield pa.RecordBatch.from_arrays([pa.array([row["section"]] * n, pa.int32()), pa.array([row["shard_no"]] * n, pa.int64()), pa.array(rules, pa.int64()), pa.array([lvl] * n, pa.int32())], names=["section", "shard_no", "k", "lvl"])

    return index.shards.select(*CORE).mapInArrow(run, "section int, shard_no long, k long, lvl int")


def count(index: TreeIndex, path: str) -> DataFrame:
    """(doc_id, n) for an index built with the ``no_start`` compressor."""
    spark, a = index.spark, compile_path(path)
    table = spark.createDataFrame([(s, k, n, int(sel), [down, right]) for s, k, n, sel, down, right in a.rows()], "q int, kind int, name string, n long, holes array<int>")
    named = [n for k, n in a.classes if n is not None]
    shards = index.shards.select("section", "shard_no", "kinds", "names", "rules", "start", "doc_ids", "doc_start")
    labels = shards.select("section", "shard_no", F.posexplode(F.arrays_zip("kinds", "names")).alias("sym", "l")).select("section", "shard_no", F.col("sym").cast("long").alias("sym"), F.col("l.kinds").alias("kind"), F.col("l.names").alias("label"))
    key = F.when(F.col("label").isin(named), F.col("label"))
    own = labels.withColumn("name", key if named else F.lit(None).cast("string")).alias("l").join(F.broadcast(table).alias("t"), (F.col("l.kind") == F.col("t.kind")) & F.col("l.name").eqNullSafe(F.col("t.name"))).select("section", "shard_no", "sym", "q", "n", "holes")  # a row for each state and class
    states = spark.range(a.n_states).select(F.col("id").cast("int").alias("q"))
    none = shards.select("section", "shard_no", F.size("names").cast("long").alias("sym")).crossJoin(F.broadcast(states)).select("section", "shard_no", "sym", "q", F.lit(0).cast("long").alias("n"), F.array().cast("array<int>").alias("holes"))  # states of one automaton
    done = written(spark, own.unionByName(none), "behaviours")
    rules = shards.select("section", "shard_no", F.size("names").cast("long").alias("labels"), F.posexplode("rules").alias("k", "rule")).select("section", "shard_no", F.col("k").cast("long").alias("k"), (F.col("labels") + 2 + F.col("k")).alias("sym"), rule_outer(F.col("rule")).alias("x"), rule_hole(F.col("rule")).cast("int").alias("i"), rule_inner(F.col("rule")).alias("y"))
    rules = written(spark, rules.join(rule_levels(index), ["section", "shard_no", "k"]), "rules")
    parts = [done]
    for lvl in range(1, (rules.agg(F.max("lvl")).first()[0] or 0) + 1):
        known = parts[0]
        for p in parts[1:]:
            known = known.unionByName(p)
        outer = known.select("section", "shard_no", F.col("sym").alias("x"), "q", F.col("n").alias("nx"), F.col("holes").alias("hx"))
        inner = known.select("section", "shard_no", F.col("sym").alias("y"), F.col("q").alias("below"), F.col("n").alias("ny"), F.col("holes").alias("hy"))
        now = rules.where(F.col("lvl") == lvl).join(outer, ["section", "shard_no", "x"]).withColumn("below", F.get("hx", F.col("i") - 1)).join(inner, ["section", "shard_no", "y", "below"])
        holes = F.concat(F.slice("hx", F.lit(1), F.col("i") - 1), F.col("hy"), F.slice("hx", F.col("i") + 1, F.size("hx")))
        parts.append(written(spark, now.select("section", "shard_no", "sym", "q", (F.col("nx") + F.col("ny")).alias("n"), holes.alias("holes")), "behaviours"))
    known = parts[0]
    for p in parts[1:]:
        known = known.unionByName(p)
    docs = shards.select("section", "shard_no", F.explode(F.arrays_zip("doc_ids", F.slice("doc_start", F.lit(1), F.size("doc_ids")).alias("at"))).alias("d"), "start").select("section", "shard_no", F.col("d.doc_ids").alias("doc_id"), F.get("start", F.col("d.at")).cast("long").alias("sym"))
    return docs.join(known.where(F.col("q") == a.initial), ["section", "shard_no", "sym"]).select("doc_id", "n")
