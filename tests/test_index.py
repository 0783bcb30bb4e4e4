import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from treegrammar import queries
from treegrammar.baselines import labels_twigs, node_table, path_index
from treegrammar.operators.index import TreeIndex, assign_shards
from treegrammar.operators.relational import expanded_sizes, relational_pairs, shared_subtrees
from treegrammar.plans import planner
from treegrammar.sources.carriers import Carrier, Spine, carrier
from treegrammar.workloads import MARKET, index, nodes

#: Counts on the smallest tables, worked out independently.
COUNTS = {
    "q03": 91, "q04": 1799, "q05": 593, "q06": 150, "q07": 3100, "q08": 589, "q13": 30504, "q14": 30503, "q15": 28888, "q16": 14450, "x1": 51, "x2": 1070, "x3": 1070, "simple_q1": 106,
    "simple_q2": 1007, "simple_q3": 360, "simple_q4": 7575, "label_price": 493, "label_keyword": 3822, "label_attrs": 3616, "fsib_listitem": 4302,
}


def n_of(df):
    return df.first()["n"]


def test_counts(spark, sf):
    for name, n in COUNTS.items():
        assert n_of(index(spark, sf, "market").count(MARKET[name][0])) == n, name


@pytest.mark.parametrize("shard_nodes", [1500, 20_000])
def test_shards_change_no_answer(spark, sf, shard_nodes):
    ix = index(spark, sf, "market", shard_nodes=shard_nodes)
    for name in ("q05", "q07", "fsib_listitem", "x1"):
        assert n_of(ix.count(MARKET[name][0])) == COUNTS[name]
        for options in ({"mode": "lazy"}, {"mode": "lazy", "jump": False, "prune": False}):
            assert n_of(ix.count(MARKET[name][0], **options)) == COUNTS[name]
    assert ix.materialize("//listitem/following-sibling::listitem").count() == COUNTS["fsib_listitem"]
    whole = "".join(r["xml"] for r in ix.serialize("/site").orderBy("piece_no").collect())
    assert whole.startswith("<site><regions><africa>") and whole.endswith("</closed_sales></site>") and whole.count("<keyword>") == COUNTS["label_keyword"]


def test_materialized_numbers_are_those_of_the_node_table(spark, sf):
    ix, table = index(spark, sf, "market", shard_nodes=5000), nodes(spark, sf, "market")
    for path in (MARKET["q07"][0], MARKET["simple_q3"][0], "/site/regions/*/shop", "/site/*"):
        mine = {(r["node"], r["pre"]) for r in ix.materialize(path).select("node", "pre").collect()}
        theirs = {(r["node"], r["pre"]) for r in node_table.select(table, path).select("node", "pre").collect()}
        assert mine == theirs, path
    assert table.select("node").distinct().count() == table.count() == 54952


def test_label_row_limit_stops_early(spark, sf):
    got = index(spark, sf, "market").materialize("//keyword", limit=5).collect()
    every = index(spark, sf, "market").materialize("//keyword").orderBy("node").limit(5).collect()
    assert got == every


def test_baselines(spark, sf):
    t = nodes(spark, sf, "market")
    for name in ("q05", "q15", "fsib_listitem", "x2"):
        assert n_of(node_table.count(t, MARKET[name][0])) == COUNTS[name]
    positions = labels_twigs.label_positions(t)
    assert n_of(labels_twigs.label_count(positions, "keyword")) == COUNTS["label_keyword"]
    europe = t.where("path = '/site/regions/europe'").first()
    assert n_of(labels_twigs.label_count(positions, "keyword", (europe["node"], europe["node"] + europe["size"]))) == COUNTS["q03"]
    paths = path_index.build(t)
    assert n_of(path_index.count(paths, "//closed_sale/price")) == COUNTS["label_price"]
    assert n_of(path_index.count(paths, "/closed_sale/price")) == 0
    summary = path_index.summary(t, 2)
    assert n_of(path_index.estimate(summary, MARKET["q03"][0], 2)) >= COUNTS["q03"]
    assert path_index.summary(t, per_label={"keyword": 3}, k=1).where("path like '%keyword'").count() > 1


def test_planner(spark, sf):
    ix = index(spark, sf, "market")
    t = nodes(spark, sf, "market")
    paths, totals = path_index.build(t), planner.label_totals(ix)
    assert planner.anchor_root(ix, "//site/categories/category") == "/site/categories/category"
    for path, method, n in (("//keyword", "label_total", 3822), ("//site/categories/category", "simple_path", 106), ("//listitem//keyword", "rule_wise", 3100)):
        plan = planner.plan_count(ix, path, paths, totals)
        assert plan.method == method and n_of(planner.run_count(ix, plan, paths, totals)) == n
    assert "rule_wise" in planner.explain(ix, planner.plan_count(ix, "//listitem//keyword"))


def test_pruned_scan(spark, sf):
    """A count reads the columns of the grammar only, and the label filter stands before the kernel."""
    df = index(spark, sf, "pages").count("//ul//a")
    plan = df._jdf.queryExecution().executedPlan().toString()
    scan = plan[plan.index("ReadSchema") :]
    assert "texts" not in scan and "jump" not in scan and "array_contains" in plan


def test_documents_with_awkward_content(spark):
    rows = [("x", 0, k, k, c) for k, c in enumerate(["", None, "<a/>", "<a>&lt;&amp;</a>", '<a k="&quot;"><b/>t</a>', "<a>" * 400 + "</a>" * 400])]
    df = spark.createDataFrame(rows, "carrier string, section int, ord long, doc_id long, content string")
    ix = TreeIndex.build(spark, Carrier("x", df))
    assert {r["doc_id"]: r["n"] for r in ix.count("//a", by="doc").collect()} == {0: 0, 1: 0, 2: 1, 3: 1, 4: 1, 5: 400}
    docs = {r["doc_id"]: r["xml"] for r in ix.documents().collect()}
    assert docs[0] == docs[1] == "" and docs[3] == "<a>&lt;&amp;</a>" and docs[4] == '<a k="&quot;"><b/>t</a>'
    assert [r["xml"] for r in ix.serialize("//a/@k").collect()] == ['k="&quot;"']
    assert ix.get_text(4, 0).first()["value"] == '"' and ix.get_text(4, 1).first()["value"] == "t"
    assert ix.locate(4, 1).first()["label"] == "b"
    assert ix.count("//zz").first()["n"] == 0 and ix.materialize("//zz").count() == 0


def test_empty_tables(spark):
    df = spark.createDataFrame([], "carrier string, section int, ord long, doc_id long, content string")
    for spine in (None, Spine("top", [Spine("list", section=0)])):
        ix = TreeIndex.build(spark, Carrier("none", df, spine))
        assert ix.count("//a").first()["n"] == 0
        assert ix.count("//list").first()["n"] == (1 if spine else 0)
        assert ix.materialize("//*").count() == (2 if spine else 0)


def test_shard_numbers_follow_the_order(spark):
    df = spark.range(1000).select(F.lit("x").alias("carrier"), F.lit(0).alias("section"), F.col("id").alias("ord"), F.col("id").alias("doc_id"), F.expr("repeat('<a/>', cast(id % 7 as int) + 1)").alias("content"))
    got = [r["shard_no"] for r in assign_shards(df, 500).orderBy("ord").collect()]
    assert got == sorted(got) and len(set(got)) > 5


def test_relational_variants(spark, sf):
    t = nodes(spark, sf, "threads")
    kinds = shared_subtrees(spark, t)
    assert kinds.agg(F.sum("n")).first()[0] == t.count() and kinds.count() < t.count() / 2
    left, rules, none = relational_pairs(spark, t)
    # What a rule stands for: its own two symbols and theirs; together they hold every node once.
    weight = expanded_sizes(rules, none)
    counts = {r["sym"]: r["count"] for r in left.groupBy("sym").count().collect()}
    assert sum(n * weight.get(s, 1) for s, n in counts.items()) == t.count() and left.where(F.col("sym") != none).count() < t.count() / 2
    # No pair within the rank bound is left, but those of equal symbols.
    rank = {x: 2 for x in range(none)} | {none: 0}
    for x, _, y, z in rules:
        rank[z] = rank[x] + rank[y] - 1
    up = left.select("doc_id", F.col("id").alias("parent"), F.col("sym").alias("outer"))
    pairs = left.join(up, ["doc_id", "parent"]).groupBy("outer", "slot", "sym").count().collect()
    assert all(r["count"] <= 3 or r["outer"] == r["sym"] or rank[r["outer"]] + rank[r["sym"]] > 4 for r in pairs)
    holes = left.groupBy("doc_id", F.col("parent").alias("id")).agg(F.sort_array(F.collect_list("slot")).alias("slots"))
    assert all(list(r["slots"] or []) == list(range(1, rank[r["sym"]] + 1)) for r in left.join(holes, ["doc_id", "id"], "left").collect())


def test_carriers(spark, sf):
    expected = {"threads": {"//turn": 87, "//reply//kw": 232, "//say": 207}, "pages": {"//*": 1801, "//a": 281, "//p//p": 0, "//@*": 431}, "log": {"//day": 397, "//click": 210}, "prose": {"//doc": 200, "//para": 1829, "//sent/*": 79047}, "vectors": {"//dim": 32000}}
    for name, paths in expected.items():
        for path, n in paths.items():
            assert n_of(index(spark, sf, name).count(path)) == n, (name, path)
    assert carrier(spark, "vectors", sf).spine is None


def test_entry_and_registry(spark, sf):
    assert queries.entry(spark, sf).agg(F.sum("n")).first()[0] == 232
    assert set(queries.oracle_sql()) <= set(queries.queries())


def test_joined_places_give_the_same(spark, sf, monkeypatch):
    """Beyond the bound on shipped shards the places are joined instead."""
    from treegrammar.operators import index as module

    ix = TreeIndex.load(spark, index(spark, sf, "market", shard_nodes=5000).path)
    path = "//listitem/following-sibling::listitem"
    mine = sorted(r["node"] for r in ix.materialize(path).collect())
    monkeypatch.setattr(module, "SHIPPED_SHARDS", 0)
    other = TreeIndex.load(spark, ix.path)
    assert sorted(r["node"] for r in other.materialize(path).collect()) == mine
    assert other.serialize("//price").count() == COUNTS["label_price"] and other.nodes().select("node").distinct().count() == 54952
    assert other.resident().count("//keyword") == COUNTS["label_keyword"] and other.resident(10) is None
    assert {r["path"]: r["n"] for r in other.count_many(["//keyword", "/site/regions", path]).collect()} == {"//keyword": 3822, "/site/regions": 1, path: 4302}


@pytest.mark.parametrize("kind", ["outlier", "equal", "dense run", "even", "two ends"])
def test_shards_under_skewed_keys(spark, kind):
    """No shard exceeds twice the target, and shards are contiguous in the order of the keys."""
    n, target = 3000, 400
    keys = {"outlier": [*range(n - 1), 10**12], "equal": [7] * n, "dense run": [*range(0, 10**9, 10**6), *range(5 * 10**8, 5 * 10**8 + n)], "even": [k * 1000 for k in range(n)], "two ends": [*range(n), *range(1 << 40, (1 << 40) + n)]}[kind]
    df = spark.createDataFrame([(0, k, i, "<a><b/></a>") for i, k in enumerate(keys)], "section int, ord long, doc_id long, content string")
    got = assign_shards(df, target).select("shard_no", "ord", "doc_id").collect()
    assert len(got) == len(keys) and sorted(r["doc_id"] for r in got) == list(range(len(keys)))
    sizes, order = {}, sorted((r["ord"], r["shard_no"]) for r in got)
    for _, s in order:
        sizes[s] = sizes.get(s, 0) + 5
    assert max(sizes.values()) <= 2 * target and len(sizes) >= len(keys) * 5 / (2 * target)
    if kind != "equal":
        assert [s for _, s in order] == sorted(s for _, s in order)


def test_label_count_within_a_subtree_reads_its_shards(spark, sf):
    ix = index(spark, sf, "market", shard_nodes=5000)
    top = nodes(spark, sf, "market").where("path = '/site/regions/europe'").select("node", "size").first()
    own = ix._clipped(0, top["node"], top["node"] + top["size"])
    assert n_of(ix.label_count("keyword", (0, top["node"], top["size"]))) == COUNTS["q03"]
    assert 0 < own.shards.count() < ix.shards.count() / 2


def test_lazy_materialization_jumps(spark, sf):
    import numpy as np

    from treegrammar.operators.index import load_shard
    from treegrammar.views.chunkwise import Chunkwise
    from treegrammar.views.rulewise import Run
    from treegrammar.xpath.automaton import compile_path

    row = index(spark, sf, "threads").shards.first().asDict()
    g, a = load_shard(row), compile_path("//reply//kw")
    runs = {j: Run(g, a, j) for j in (True, False)}
    eager = Chunkwise(Run(g, a)).materialize()[0]
    for r in runs.values():
        assert all(np.array_equal(x, y) for x, y in zip(Chunkwise(r, lazy=True).materialize()[0], eager, strict=True))
    assert runs[True].count.visited < runs[False].count.visited


def test_compared_agrees_with_the_indexes(spark, sf):
    """One pass over the records gives every compressor the figures of its own index."""
    from treegrammar.sources.carriers import carrier

    variants = [("pairs", 2), ("no_start", 2), ("dag", 2), ("one_rule", 2)]
    got = TreeIndex.compared(spark, carrier(spark, "threads", sf), variants)
    assert got.count() == len(variants) * index(spark, sf, "threads").shards.count()
    for c, r in variants:
        own, one = index(spark, sf, "threads", c, r).stats(), got.where(F.col("variant") == f"{c}/{r}").drop("variant")
        assert sorted(map(tuple, one.select(*own.columns).collect())) == sorted(map(tuple, own.collect()))


def test_relational_round_writes_its_trees_only(spark, sf, monkeypatch):
    """A round needs no table of its edges beside the contracted trees."""
    from treegrammar.operators import relational as module

    t, names, write = nodes(spark, sf, "threads"), [], module.written
    monkeypatch.setattr(module, "written", lambda s, df, name: names.append(name) or write(s, df, name))
    _, rules, _ = relational_pairs(spark, t, 2)
    assert names == ["pairs"] * 3 and len(rules) > 2


def test_row_groups_of_the_index_are_bounded(spark, sf, monkeypatch):
    """A task that writes several shards does not hold them all until its file ends."""
    monkeypatch.setattr("treegrammar.operators.index.ROW_GROUP_BYTES", 1 << 16, raising=False)
    ix = TreeIndex.build(spark, carrier(spark, "market", sf), None, "one_rule", shard_nodes=1500)
    files = [pq.ParquetFile(f.removeprefix("file://")).metadata for f in ix.shards.inputFiles()]
    assert sum(f.num_rows for f in files) > 2 * len(files)
    assert sum(f.num_row_groups for f in files) > 2 * len(files) and all(f.row_group(k).num_rows <= 4 for f in files for k in range(f.num_row_groups))
    assert n_of(ix.count(MARKET["q07"][0])) == COUNTS["q07"]


def test_relational_rounds_of_few_edges_shuffle_no_trees(spark, sf, monkeypatch):
    """Messages along few edges go to the trees by a broadcast, those along many by a shuffle, with the same trees and rules."""
    from treegrammar.operators import relational as module

    t, plans, write = nodes(spark, sf, "threads"), [], module.written
    monkeypatch.setattr(module, "written", lambda s, df, name: plans.append(df._jdf.queryExecution().sparkPlan().toString()) or write(s, df, name))
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        left, rules, _ = relational_pairs(spark, t, 3)
        assert len(plans) == 4 and all("BroadcastHashJoin" in p and "SortMergeJoin" not in p for p in plans[1:])
        plans.clear()
        monkeypatch.setattr(module, "BROADCAST_EDGES", 0)
        many, same, _ = relational_pairs(spark, t, 3)
        assert all("SortMergeJoin" in p for p in plans[1:])
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)
    assert rules == same and sorted(map(tuple, left.collect())) == sorted(map(tuple, many.collect()))
