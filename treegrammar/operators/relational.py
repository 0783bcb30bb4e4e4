"""Relational operators around the tree methods: joins, windows, set operations, grouping sets, closures, as-of joins.

Each function is an operator on DataFrames; ``queries`` applies them to the given tables.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from treegrammar.shared import written
from treegrammar.sources.carriers import table
from treegrammar.workloads import index
from treegrammar.workloads import nodes as nodes_of


def as_of(left: DataFrame, right: DataFrame, key: str, ts: str, value: str, out: str) -> DataFrame:
    """For every left row the latest right value of the same key that is not later: one sort by key and time, no range join.

    The rows of both sides go into one stream; at equal times right rows come first."""
    a = left.select(*left.columns, F.lit(1).alias("__side"), F.lit(None).cast(right.schema[value].dataType).alias("__v"))
    b = right.select(*[F.col(c) if c in (key, ts) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.lit(0).alias("__side"), F.col(value).alias("__v"))
    w = Window.partitionBy(key).orderBy(ts, "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return a.unionByName(b).withColumn(out, F.last("__v", ignorenulls=True).over(w)).where("__side = 1").drop("__side", "__v")


def with_child(nodes: DataFrame, label: str, child: str) -> DataFrame:
    """Elements with a label that have a child with another: a semi-join."""
    up = nodes.where((F.col("label") == child) & (F.col("kind") == 0)).select(F.col("doc_id").alias("d"), F.col("parent").alias("p"))
    own = nodes.where((F.col("label") == label) & (F.col("kind") == 0))
    return own.join(up, (own["doc_id"] == up["d"]) & (own["node"] == up["p"]), "left_semi")


def without_attributes(nodes: DataFrame, label: str) -> DataFrame:
    """Elements with a label and no attribute node below: an anti-join."""
    up = nodes.where("kind = 2").select(F.col("doc_id").alias("d"), F.col("parent").alias("p"))
    own = nodes.where((F.col("label") == label) & (F.col("kind") == 0))
    return own.join(up, (own["doc_id"] == up["d"]) & (own["node"] == up["p"]), "left_anti")


def sibling_ordinals(nodes: DataFrame) -> DataFrame:
    """Each node with its place among its siblings and the next sibling's number."""
    w = Window.partitionBy("doc_id", "parent").orderBy("node")
    return nodes.withColumn("ordinal", F.row_number().over(w)).withColumn("next_node", F.lead("node").over(w))


def binary_encoding(nodes: DataFrame) -> DataFrame:
    """First child and next sibling of every node (null if there is none)."""
    return sibling_ordinals(nodes).select("*", F.when(F.col("size") > 1, F.col("node") + 1).alias("fc")).withColumnRenamed("next_node", "ns")


def ancestors(spark: SparkSession, nodes: DataFrame, label: str) -> DataFrame:
    """(doc_id, node, ancestor) of all pairs of elements with a label, one level of parents a round until none is left."""
    up = written(spark, nodes.where("parent is not null").select("doc_id", "node", "parent"), "parents")
    own = nodes.where((F.col("label") == label) & (F.col("kind") == 0)).select("doc_id", "node")
    now = own.join(up, ["doc_id", "node"]).select("doc_id", "node", F.col("parent").alias("ancestor"))
    out = None
    while True:
        now = written(spark, now, "closure")
        if now.isEmpty():
            break
        hit = now.join(own.withColumnRenamed("node", "ancestor"), ["doc_id", "ancestor"], "left_semi").select("doc_id", "node", "ancestor")
        out = hit if out is None else out.unionByName(hit)
        above = up.select("doc_id", F.col("node").alias("ancestor"), "parent")
        now = now.join(above, ["doc_id", "ancestor"]).select("doc_id", "node", F.col("parent").alias("ancestor"))
    return out if out is not None else now


def shared_subtrees(spark: SparkSession, nodes: DataFrame) -> DataFrame:
    """(signature, n): every distinct subtree of the unranked trees with its occurrences, level by level from the deepest.

    A signature is a digest of the label and the children's signatures in order; only one level is joined at a time."""
    rows = written(spark, nodes.select("doc_id", "node", "parent", "kind", "label", "path").withColumn("depth", F.size(F.split("path", "/"))).drop("path"), "dag-nodes")
    deepest = rows.agg(F.max("depth")).first()[0] or 0
    done, below = None, None
    for d in range(deepest, 0, -1):
        level = rows.where(F.col("depth") == d)
        if below is not None:
            kids = below.groupBy("doc_id", F.col("parent").alias("node")).agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("node", "sig"))), lambda s: s["sig"]), ",").alias("kids"))
            level = level.join(kids, ["doc_id", "node"], "left")
        else:
            level = level.withColumn("kids", F.lit(""))
        below = written(spark, level.select("doc_id", "node", "parent", F.sha2(F.concat_ws("|", F.col("kind").cast("string"), "label", F.coalesce("kids", F.lit(""))), 256).alias("sig")), "dag-level")
        done = below.select("sig") if done is None else done.unionByName(below.select("sig"))
    return done.groupBy(F.col("sig").alias("signature")).agg(F.count("*").alias("n"))


#: Edges of a round whose messages are broadcast; more are joined by a shuffle.
BROADCAST_EDGES = 100_000

#: How often each triple occurs that keeps to the rank bound.
_TRIPLES = """SELECT outer, slot, sym, count(*) AS n FROM {now} WHERE outer <> sym AND outer_rank + sym_rank <= 4
GROUP BY outer, slot, sym, outer_rank, sym_rank HAVING n > {least} ORDER BY n DESC, outer, slot, sym LIMIT {limit}"""
#: A round's contraction. A row knows by itself whether it goes, as it holds its triple, and an outer symbol has one triple in a round; no symbol is
#: outer and inner, so a node that grows is told so once, and one below hears of one edge at most: its parent is gone (then ``into`` has the new one) or grown.
_CONTRACTED = """WITH n AS (SELECT *, try_element_at({picks}, outer) AS p FROM {now}),
edge AS (SELECT doc_id, id, parent, p.at, p.made, sym_rank AS grow, outer_rank + sym_rank - 1 AS made_rank FROM n WHERE p.at = slot AND p.inner = sym),
own AS (SELECT doc_id, parent AS id, made, made_rank FROM edge),
above AS (SELECT doc_id, stack(2, id, parent, parent, CAST(NULL AS BIGINT)) AS (parent, into), at, made, grow, made_rank FROM edge)
SELECT {hint} n.doc_id, coalesce(above.into, n.parent) AS parent, n.id, coalesce(own.made, n.sym) AS sym,
    CASE WHEN above.into IS NOT NULL THEN above.at + n.slot - 1 WHEN n.slot > above.at THEN n.slot + above.grow - 1 ELSE n.slot END AS slot,
    coalesce(above.made, n.outer) AS outer, coalesce(own.made_rank, n.sym_rank) AS sym_rank, coalesce(above.made_rank, n.outer_rank) AS outer_rank
FROM n LEFT JOIN own ON n.doc_id = own.doc_id AND n.id = own.id LEFT JOIN above ON n.doc_id = above.doc_id AND n.parent = above.parent
WHERE NOT coalesce(p.at = n.slot AND p.inner = n.sym, false)"""


def relational_pairs(spark: SparkSession, nodes: DataFrame, rounds: int | None = None, best: int = 24, least: int = 3) -> tuple[DataFrame, list[tuple[int, int, int, int]], int]:
    """Pair replacement without a kernel, for one tree that no task could hold: (doc_id, id, sym, parent, slot), the rules, and the symbol of absent subtrees.

    Every node carries the symbol above it and both ranks, so a round counts all triples by one partial aggregation without a join,
    takes the most frequent compatible ones (a short list), and contracts their edges by two joins with what happened to a node or the one
    above: gone into the next above, or grown. The counts tell how many edges these are; most rounds contract few, which go to the rows by a
    broadcast, so that the trees stay where they are. So it goes until no triple occurs more than ``least`` times (``rounds`` stops earlier). Absent
    subtrees are nodes of rank zero, so that ranks, bounded by three, fall where labels have fewer than two subtrees.
    Triples of equal symbols would need chain parities and are left to later levels of the labels around them."""
    labels = [r["label"] for r in nodes.select(F.concat(F.col("kind").cast("string"), F.lit(":"), "label").alias("label")).distinct().orderBy("label").collect()]
    number = F.array_position(F.array(*[F.lit(x) for x in labels]), F.concat(F.col("kind").cast("string"), F.lit(":"), "label")) - 1
    enc = binary_encoding(nodes)
    w = Window.partitionBy("doc_id", "parent").orderBy("node")
    prev = F.lag("node").over(w)
    none = len(labels)
    base = enc.select("doc_id", F.col("node").cast("long").alias("id"), number.cast("int").alias("sym"), F.coalesce(prev, F.col("parent")).cast("long").alias("parent"), F.when(prev.isNotNull(), 2).otherwise(1).alias("slot"))
    open_ = F.array_compact(F.array(F.when(F.col("fc").isNull(), F.lit(1)), F.when(F.col("ns").isNull(), F.lit(2))))
    absent = enc.select("doc_id", F.col("node").cast("long").alias("parent"), F.explode(open_).alias("slot"))
    absent = absent.select("doc_id", (-2 * F.col("parent") - F.col("slot")).alias("id"), F.lit(none).alias("sym"), "parent", "slot")
    first = base.unionByName(absent).withColumn("sym_rank", F.when(F.col("sym") == none, 0).otherwise(2))
    up = base.select("doc_id", F.col("id").alias("parent"), F.col("sym").alias("outer"), F.lit(2).alias("outer_rank"))
    now, rules, n_symbols = written(spark, first.join(up, ["doc_id", "parent"], "left"), "pairs"), [], none + 1
    while rounds is None or rounds > 0:
        rounds = None if rounds is None else rounds - 1
        chosen, outers, inners, edges = [], set(), set(), 0
        for x, i, y, n in spark.sql(_TRIPLES, now=now, least=least, limit=8 * best).collect():
            if x in outers or x in inners or y in outers or len(chosen) == best:
                continue
            chosen.append((x, i, y, n_symbols + len(chosen)))
            outers.add(x)
            inners.add(y)
            edges += n
        if not chosen:
            break
        rules += chosen
        n_symbols += len(chosen)
        # A constant of at most ``best`` entries: it costs no job, and the compiled code is that of the round before.
        picks = "map(" + ", ".join(f"{x}, named_struct('at', {i}, 'inner', {y}, 'made', {z})" for x, i, y, z in chosen) + ")"
        hint = "/*+ BROADCAST(own), BROADCAST(above) */" if edges <= BROADCAST_EDGES else ""  # one row an edge and two
        now = written(spark, spark.sql(_CONTRACTED.replace("{picks}", picks).replace("{hint}", hint), now=now), "pairs")
    return now.select("doc_id", "id", "sym", "parent", "slot"), rules, none


def _asof(spark: SparkSession, sf: str) -> DataFrame:
    ev = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    buys = ev.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    clicks = ev.where("event_type = 'click'").select("user_id", "ts", F.col("ts").alias("click_ts"))
    return as_of(buys, clicks, "user_id", "ts", "click_ts", "last_click").select("event_id", F.unix_micros("last_click").alias("last_click"))


def _results(spark: SparkSession, sf: str, path: str) -> DataFrame:
    return index(spark, sf, "threads").materialize(path).select("doc_id", "pre")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    thread_nodes = lambda s, d: nodes_of(s, d, "threads")
    page_nodes = lambda s, d: nodes_of(s, d, "pages")
    n_of = lambda df: df.agg(F.count("*").alias("n"))
    return {
        "rel_asof_last_click": _asof,
        "rel_semi_ul_li": lambda s, d: with_child(page_nodes(s, d), "ul", "li").groupBy("doc_id").agg(F.count("*").alias("n")),
        "rel_anti_li": lambda s, d: n_of(without_attributes(page_nodes(s, d), "li")),
        "rel_window_ordinals": lambda s, d: sibling_ordinals(thread_nodes(s, d)).where("label = 'say'").groupBy("doc_id").agg(F.sum(F.when(F.col("next_node").isNull(), 0).otherwise(1)).alias("with_next"), F.count("*").alias("n")),
        "rel_union": lambda s, d: n_of(_results(s, d, "//kw").union(_results(s, d, "//say")).distinct()),
        "rel_intersect": lambda s, d: n_of(_results(s, d, "//turn").intersect(_results(s, d, "//reply/turn"))),
        "rel_except": lambda s, d: _results(s, d, "//turn").exceptAll(_results(s, d, "//reply/turn")).groupBy("doc_id").agg(F.count("*").alias("n")),
        "rel_cube": lambda s, d: index(s, d, "prose").count("//para", by="doc").join(table(s, d, "labels"), "doc_id").cube("quality", "toxic").agg(F.sum("n").alias("n")),
        "rel_pivot": lambda s, d: page_nodes(s, d).where("kind = 0 and label in ('a', 'p', 'li')").groupBy("doc_id").pivot("label", ["a", "li", "p"]).count().na.fill(0),
        "rel_topk_labels": lambda s, d: nodes_of(s, d, "log").where("kind = 0 and label in ('click', 'error', 'purchase', 'signup', 'view')").groupBy("label").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "label").limit(3),
        "rel_distinct_paths": lambda s, d: nodes_of(s, d, "vectors").agg(F.countDistinct("path").alias("n")),
        "rel_closure_turns": lambda s, d: ancestors(s, thread_nodes(s, d), "turn").groupBy("doc_id").agg(F.count("*").alias("n")),
        "rel_percentile_levels": lambda s, d: thread_nodes(s, d).where("label = 'turn'").agg(F.max("level").alias("deepest"), F.min("level").alias("top"), F.percentile("level", 0.75).alias("p75")),
        "rel_shared_subtrees": lambda s, d: shared_subtrees(s, nodes_of(s, d, "threads")).agg(F.sum("n").alias("nodes"), F.count("*").alias("kinds")),
        "rel_pairs_triples": _pairs_report,
        "rel_pairs_lossless": _pairs_lossless,
    }


def _pairs_report(spark: SparkSession, sf: str) -> DataFrame:
    """Nodes and absent subtrees left by relational pair replacement, and the rules made (no oracle: the sizes are the result)."""
    left, rules, none = relational_pairs(spark, nodes_of(spark, sf, "threads"))
    return left.agg(F.sum((F.col("sym") != none).cast("long")).alias("nodes_left"), F.sum((F.col("sym") == none).cast("long")).alias("absent_left")).withColumn("rules", F.lit(len(rules)))


def expanded_sizes(rules: list[tuple[int, int, int, int]], none: int) -> dict[int, int]:
    """The nodes of the tree that each rule's symbol stands for."""
    size = {none: 0}
    for x, _, y, z in rules:
        size[z] = size.get(x, 1) + size.get(y, 1)
    return size


def _pairs_lossless(spark: SparkSession, sf: str) -> DataFrame:
    """The nodes that the contracted trees stand for."""
    left, rules, none = relational_pairs(spark, nodes_of(spark, sf, "threads"))
    size = spark.createDataFrame(list(expanded_sizes(rules, none).items()), "sym int, nodes int")
    return left.join(F.broadcast(size), "sym", "left").agg(F.sum(F.coalesce("nodes", F.lit(1))).alias("nodes"))  # one row a rule


def oracle_sql() -> dict[str, str]:
    lines = "len(string_split(text, chr(10)))"
    kw = "len(regexp_extract_all(text, '[A-Za-z]{10,}'))"
    return {
        "rel_asof_last_click": "SELECT p.event_id, epoch_us(max(c.ts)) AS last_click FROM events p LEFT JOIN events c ON c.user_id = p.user_id AND c.ts <= p.ts AND c.event_type = 'click' WHERE p.event_type = 'purchase' GROUP BY 1",
        "rel_semi_ul_li": "SELECT page_id AS doc_id, CAST(len(regexp_extract_all(html, '<ul[ >]')) AS BIGINT) AS n FROM pages WHERE html LIKE '%<li>%'",
        "rel_anti_li": "SELECT CAST(sum(len(regexp_extract_all(html, '<li[ >]'))) AS BIGINT) AS n FROM pages",
        "rel_window_ordinals": f"SELECT conv_id AS doc_id, CAST(sum({lines}) - 1 AS BIGINT) AS with_next, CAST(sum({lines}) AS BIGINT) AS n FROM conversations GROUP BY 1",
        "rel_union": f"SELECT CAST(sum({lines} + {kw}) AS BIGINT) AS n FROM conversations",
        "rel_intersect": "SELECT count(*) AS n FROM conversations WHERE turn > 0",
        "rel_except": "SELECT conv_id AS doc_id, count(*) AS n FROM conversations WHERE turn = 0 GROUP BY 1",
        "rel_cube": f"SELECT quality, toxic, CAST(sum({lines}) AS BIGINT) AS n FROM documents JOIN labels USING (doc_id) GROUP BY CUBE (quality, toxic)",
        "rel_pivot": "SELECT page_id AS doc_id, " + ", ".join(f"CAST(len(regexp_extract_all(html, '<{t}[ >]')) AS BIGINT) AS {t}" for t in ("a", "li", "p")) + " FROM pages",
        "rel_topk_labels": "SELECT event_type AS label, count(*) AS n FROM events GROUP BY 1 ORDER BY n DESC, label LIMIT 3",
        "rel_distinct_paths": "SELECT CAST(6 AS BIGINT) AS n",
        "rel_closure_turns": "SELECT conv_id AS doc_id, CAST(count(*) * (count(*) - 1) / 2 AS BIGINT) AS n FROM conversations GROUP BY 1 HAVING count(*) > 1",
        "rel_percentile_levels": "SELECT CAST(2 * max(turn) + 1 AS BIGINT) AS deepest, CAST(1 AS BIGINT) AS top, CAST(quantile_cont(2 * turn + 1, 0.75) AS DOUBLE) AS p75 FROM conversations",
        "rel_pairs_lossless": f"SELECT CAST(sum(v) AS BIGINT) AS nodes FROM (SELECT 4 + sum(4 + 2 * {lines} + 2 * {kw}) + count(*) - 1 AS v FROM conversations GROUP BY conv_id)",
        # A subtree of a thread is told by the numbers of keywords of its lines, turn by turn; below that: keyword, text, value, and the two attributes with their holders.
        "rel_shared_subtrees": f"""WITH w AS (SELECT conv_id, turn, array_to_string(list_transform(string_split(text, chr(10)), lambda x: len(regexp_extract_all(x, '[A-Za-z]{{10,}}'))), ' ') AS says FROM conversations),
y AS (SELECT DISTINCT unnest(list_transform(string_split(text, chr(10)), lambda x: len(regexp_extract_all(x, '[A-Za-z]{{10,}}')))) AS k FROM conversations),
u AS (SELECT turn, string_agg(says, '|') OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rest FROM w)
SELECT (SELECT CAST(sum(v) AS BIGINT) FROM (SELECT 4 + sum(4 + 2 * {lines} + 2 * {kw}) + count(*) - 1 AS v FROM conversations GROUP BY conv_id)) AS nodes,
  CAST((SELECT count(*) FROM y) + (SELECT count(DISTINCT rest) FROM u) + (SELECT count(DISTINCT rest) FROM u WHERE turn > 0) + (SELECT count(DISTINCT rest) FROM u WHERE turn = 0) + 7 AS BIGINT) AS kinds""",
    }


__all__ = ["ancestors", "as_of", "binary_encoding", "queries", "oracle_sql", "relational_pairs", "shared_subtrees", "sibling_ordinals", "with_child", "without_attributes"]
