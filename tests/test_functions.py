import os
import random

import pytest
from pyspark.sql import functions as F

from tests.helpers import forest, random_path
from treegrammar.functions import tree_functions as tf
from treegrammar.grammar import compress, dictionary
from treegrammar.grammar.model import pack
from treegrammar.grammar.shape import with_parentheses
from treegrammar.measure import model_bytes, totals
from treegrammar.operators import rulewise_relational
from treegrammar.operators.index import TreeIndex, start_parentheses
from treegrammar.session import TreeGrammar
from treegrammar.sources.datasource import register
from treegrammar.views.rulewise import Run
from treegrammar.workloads import index
from treegrammar.xpath.automaton import compile_path


def test_packed_rules_in_sql(spark):
    rng = random.Random(1)
    f = forest(rng, 3, 80)
    ev, ds = f.arrays()
    g = compress.pairs(f.names, ev, ds)
    rows = [(int(w), int(x), int(i), int(y), int(r)) for w, x, i, y, r in zip(pack(g), g.outer, g.hole, g.inner, g.rank[g.first_rule :], strict=True)]
    df = spark.createDataFrame(rows, "w long, x long, i long, y long, r long")
    w = F.col("w")
    bad = df.where((tf.rule_outer(w) != F.col("x")) | (tf.rule_inner(w) != F.col("y")) | (tf.rule_hole(w) != F.col("i")) | (tf.rule_rank(w) != F.col("r")) | (tf.pack_rule(F.col("x"), F.col("i"), F.col("y"), F.col("r")) != w))
    assert bad.count() == 0 and len(rows) > 3


def test_udfs_and_table_functions(spark):
    df = spark.createDataFrame([(1, "<p>a<b>c</b><p>d"), (2, ""), (3, None)], "id int, html string")
    assert {r["id"]: r["n"] for r in df.select("id", tf.xpath_count_html("html", F.lit("//p")).alias("n")).collect()} == {1: 2, 2: 0, 3: 0}
    tokens = df.select(F.size(tf.markup_tokens("html")).alias("n")).collect()
    assert tokens[0]["n"] == 12
    TreeGrammar(spark).sql_functions()
    df.createOrReplaceTempView("some_pages")
    assert spark.sql("SELECT label FROM some_pages, LATERAL shred(html) WHERE kind = 0").count() == 3
    assert [r["xml"] for r in spark.sql("SELECT xml FROM some_pages, LATERAL xpath_results(html, '//p/b')").collect()] == ["<b>c</b>"]


def test_ordered_composition(spark):
    df = spark.createDataFrame([(3, [2, 2, 0]), (1, [1, 2, 0]), (2, [0, 0, 1])], "ord int, out array<int>")
    assert df.agg(tf.behaviour_compose("ord", "out").alias("m")).first()["m"] == [[2, 2, 0][[0, 0, 1][q]] for q in [1, 2, 0]]


def test_parentheses_for_the_shape():
    import numpy as np

    rng = random.Random(2)
    for _ in range(40):
        f = forest(rng, 2, 120)
        ev, ds = f.arrays()
        a = compile_path(random_path(rng))
        for g in (compress.one_rule(f.names, ev, ds), compress.pairs(f.names, ev, ds)):
            ends = g.start_ends().tolist()
            want = Run(g, a).lazy_count()[0].tolist()
            bp = with_parentheses(g, np.packbits(start_parentheses(g), bitorder="little").tobytes())
            assert [bp.tables["ends"][k] for k in range(len(g.start))] == ends
            assert Run(bp, a).lazy_count()[0].tolist() == want


def test_dictionary_keeps_the_trees():
    rng = random.Random(3)
    for k in range(25):
        f, sample = forest(rng, 2, 80), forest(rng, 4, 80)
        rules = dictionary.train(sample.names, *sample.arrays(), size=20)
        ev, ds = f.arrays()
        g = dictionary.pairs_with(rules)(f.names, ev, ds, k % 2 == 0)
        plain = compress.pairs(f.names, ev, ds, k % 2 == 0)
        assert g.expand().tolist() == plain.expand().tolist()


def test_relational_run(spark, sf):
    ix = index(spark, sf, "threads", "no_start")
    for path in ("//say/following-sibling::say", "//@role"):
        mine = {r["doc_id"]: r["n"] for r in rulewise_relational.count(ix, path).collect()}
        assert mine == {r["doc_id"]: r["n"] for r in ix.count(path, by="doc").collect()}


def test_data_source(spark, sf, tmp_path):
    register(spark)
    ix = index(spark, sf, "pages")
    read = spark.read.format("treegrammar_index").option("path", ix.path).option("query", "//ul//a").load()
    assert read.agg(F.sum("n")).first()[0] == 281
    assert read.where("doc_id = 3").count() == 1
    out = str(tmp_path / "xml")
    ix.documents().write.format("treegrammar_index").option("path", out).mode("append").save()
    files = [x for x in os.listdir(out) if x.endswith(".xml")]
    back = spark.read.format("xml").option("rowTag", "document").load(out)
    assert files and back.count() == 50


def test_session_and_views(spark, sf):
    tg = TreeGrammar(spark)
    docs = spark.createDataFrame([(1, "<a><b>x</b></a>"), (2, "<a/>")], "id long, xml string")
    ix = tg.build(tg.documents(docs, "id", "xml"))
    tg.tree(ix, "//b", "b_results")
    assert spark.sql("SELECT xml FROM b_results").first()["xml"] == "<b>x</b>"
    assert isinstance(tg.load(ix.path), TreeIndex) and tg.load(ix.path).count("//a").first()["n"] == 2
    assert ix.stats().first()["nodes"] == 4 and ix.selectivity("//b").first()["fraction"] == pytest.approx(1 / 3)


@pytest.mark.parametrize(("start", "rules", "labels", "map_ints", "count_mb", "all_mb"), [(88299, 39631, 89, 78084, 1.07, 1.71), (105893, 408485, 89, 871168, 7.91, 11.63)])
def test_size_model(start, rules, labels, map_ints, count_mb, all_mb):
    t = totals(model_bytes(rules, start, labels, map_ints))
    assert t["count_bytes"] / 2**20 == pytest.approx(count_mb, abs=0.01) and t["serialize_bytes"] / 2**20 == pytest.approx(all_mb, abs=0.02)
