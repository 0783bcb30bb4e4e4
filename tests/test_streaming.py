import pandas as pd
from pyspark.sql import functions as F

from treegrammar.sources.carriers import table
from treegrammar.streaming import standing


def test_standing_counts_on_a_table(spark, sf):
    got = standing.standing_counts(table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")), "//purchase/props").agg(F.sum("n")).first()[0]
    assert got == table(spark, sf, "events").where("event_type = 'purchase'").count()


def test_sliding_windows(spark, sf):
    got = standing.standing_counts(table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")), "//click", "2 days", slide="1 day").agg(F.sum("n")).first()[0]
    assert got == 2 * table(spark, sf, "events").where("event_type = 'click'").count()


def test_automaton_on_a_token_stream(spark, tmp_path):
    doc = [(0, "a"), (0, "b"), (-1, ""), (0, "c"), (0, "b"), (-1, ""), (-1, ""), (-1, "")]
    rows = [(d, k, kind, label) for d in (1, 2) for k, (kind, label) in enumerate(doc)]
    for part in range(2):
        pd.DataFrame([r for r in rows if (r[1] >= 4) == bool(part)], columns=["doc_id", "seq", "kind", "label"]).to_parquet(tmp_path / f"{part}.parquet")
    src = spark.readStream.schema("doc_id long, seq long, kind long, label string").option("maxFilesPerTrigger", 1).parquet(str(tmp_path))
    last: dict[int, int] = {}

    def keep(batch, number):
        last.update({r["doc_id"]: r["n"] for r in batch.collect()})

    standing.token_matches(src, "//a//b").writeStream.outputMode("update").foreachBatch(keep).trigger(availableNow=True).start().awaitTermination()
    assert last == {1: 2, 2: 2}


def test_stream_queries_match_their_tables(spark, sf):
    q = standing.queries()
    assert q["stream_dedup"](spark, sf).count() == table(spark, sf, "events").select("user_id", "event_type").distinct().count()
    assert q["stream_ingest_pages"](spark, sf).agg(F.sum("n")).first()[0] == 281
