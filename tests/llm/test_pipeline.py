import corpus_pipeline
from pyspark.sql import functions as F

from tests.llm.test_dedup import brute_components, brute_exact, slow_print
from tests.llm.test_text_operators import slow_overlaps
from treegrammar.llm import toxicity
from treegrammar.llm.queries import oracle_sql, queries, table


def test_pipeline_against_brute_force(spark, sf):
    docs = {r["doc_id"]: r["text"] for r in table(spark, sf, "documents").collect()}
    model = toxicity.fit(spark, table(spark, sf, "documents"), table(spark, sf, "labels"))
    left = {i: t for i, t in docs.items() if model.score(t)[0] < 0.5}
    kept = {r[0] for r in brute_exact(list(left.items())) if r[3]}
    left = {i: t for i, t in left.items() if i in kept}
    roots = brute_components({i: slow_print(t) for i, t in left.items()})
    left = {i: t for i, t in left.items() if roots[i] == i}
    items = [(r["item_id"], r["text"]) for r in table(spark, sf, "benchmark").collect()]
    block = {i for i, t in left.items() if any(w in t for w in (x[1][:60] for x in items))}
    assert all(slow_overlaps(left[i], [x for x in items if x[1][:60] in left[i]]) for i in block)
    got = {r["doc_id"]: r["n_tokens"] for r in corpus_pipeline.run(spark, sf).collect()}
    assert set(got) <= set(left) - block and len(got) > 0.7 * len(docs)
    # What decontamination dropped beyond verbatim passages really overlaps.
    for i in set(left) - block - set(got):
        assert slow_overlaps(left[i], items)


def test_stages_keep_the_columns(spark, sf):
    docs = table(spark, sf, "documents").withColumn("text", F.when(F.col("doc_id") % 7 == 0, None).otherwise(F.col("text")))
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns, name
        docs = out
    assert corpus_pipeline.STAGES[-1][1](spark, docs, sf).count() == docs.count()
    assert corpus_pipeline.STAGES[0][1](spark, docs.limit(0), sf).count() == 0


def test_every_operator_has_a_query():
    assert {int(n[2:].split("_")[0]) for n in queries()} == set(range(1, 11))
    assert set(oracle_sql()) <= set(queries())
