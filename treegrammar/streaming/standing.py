"""Streams: incremental indexing, standing path counts over event time, and an automaton that lives on a token stream."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treegrammar.operators.index import SHARD_SCHEMA, TreeIndex
from treegrammar.shared import new_path, written
from treegrammar.sources.carriers import Carrier, event_xml, table
from treegrammar.xpath.automaton import compile_path


def ingest(stream: DataFrame, make: Callable[[DataFrame], Carrier], path: str, checkpoint: str, **options):
    """Start a query that turns each micro-batch of documents into new shards of the index at ``path``.

    A batch goes to a folder of its own number and replaces it, so a batch that is run again changes nothing."""

    def batch(df: DataFrame, number: int) -> None:
        if df.isEmpty():
            return
        TreeIndex.build(df.sparkSession, make(df), f"{path}/batch={number:09d}", **options)

    return stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def ingested(spark: SparkSession, path: str, name: str) -> TreeIndex:
    """The index over all batches so far. Manifests lie beside their batch and are left out by the schema and the file pattern."""
    shards = spark.read.schema(SHARD_SCHEMA).option("pathGlobFilter", "*.parquet").parquet(f"{path}/batch=[0-9][0-9][0-9][0-9][0-9][0-9][0-9][0-9][0-9]")
    return TreeIndex(spark, shards, name)


def standing_counts(events: DataFrame, path: str, width: str = "1 day", late: str = "2 days", slide: str | None = None) -> DataFrame:
    """(window_start, n): nodes that a path selects in the fragments of the events of each window, on a stream or a table."""
    a = compile_path(path)

    def matches(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from treegrammar.grammar.compress import one_rule
        from treegrammar.sources.markup import forest_of
        from treegrammar.views.rulewise import Run

        for pdf in batches:
            forest = forest_of(list(enumerate(pdf["xml"])))
            ev, ds = forest.arrays()
            n = Run(one_rule(forest.names, ev, ds), a).eager_count()[0] if len(pdf) else []
            yield pd.DataFrame({"ts": pdf["ts"], "n": n})

    found = events.select("ts", event_xml().alias("xml")).mapInPandas(matches, "ts timestamp, n long")
    win = F.window("ts", width, slide) if slide else F.window("ts", width)
    return found.withWatermark("ts", late).groupBy(win).agg(F.sum("n").alias("n")).select(F.col("window.start").alias("window_start"), "n")


def session_counts(events: DataFrame, gap: str = "1 hour", late: str = "2 days") -> DataFrame:
    """(user_id, started, n): sessions of each user, closed by a gap."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("started"), "n")


def token_matches(tokens: DataFrame, path: str) -> DataFrame:
    """(doc_id, n): selected nodes of each document so far, kept as a stack of automaton states a document.

    ``tokens`` are (doc_id, seq, kind, label): kind 0 opens an element, -1 closes one. The state of a document is dropped
    when its last element closes."""
    a = compile_path(path)
    names: dict[str, int] = {n: k for k, (kind, n) in enumerate(a.classes) if kind == 0 and n is not None}
    other = a.classes.index((0, None))

    def update(key: tuple, pdfs: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        stack, here, n = [], a.initial, 0
        if state.exists:
            saved = state.get
            stack, here, n = list(saved[0]), saved[1], saved[2]
        for pdf in pdfs:
            for kind, label in pdf.sort_values("seq")[["kind", "label"]].itertuples(index=False):
                if kind >= 0:
                    c = names.get(label, other)
                    n += int(a.selects[here, c])
                    stack.append(int(a.to_right[here, c]))
                    here = int(a.to_down[here, c])
                else:
                    here = stack.pop()
        if stack:
            state.update((stack, here, n))
        elif state.exists:
            state.remove()
        yield pd.DataFrame({"doc_id": [key[0]], "n": [n]})

    return tokens.groupBy("doc_id").applyInPandasWithState(update, "doc_id long, n long", "stack array<int>, here int, n long", "update", "NoTimeout")


def run_to_table(df: DataFrame, spark: SparkSession, mode: str, name: str) -> DataFrame:
    """Run a streaming DataFrame over all that is there and return the sink as a table."""
    path, check = new_path(spark, name), new_path(spark, name + "-checkpoint")
    q = df.writeStream.format("parquet").outputMode(mode).option("path", path).option("checkpointLocation", check).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(path)


def _stream(spark: SparkSession, sf: str, name: str, parts: int = 4) -> DataFrame:
    """A given table as a stream of ordered files in a shared folder."""
    src = table(spark, sf, name)
    folder = new_path(spark, f"stream-{name}")
    src.repartition(parts).write.parquet(folder)
    return spark.readStream.schema(src.schema).option("maxFilesPerTrigger", 1).parquet(folder)


def _standing(spark: SparkSession, sf: str) -> DataFrame:
    """Windows of a day, all batches in one table: complete mode through foreachBatch keeps the last state."""
    folder = new_path(spark, "standing")
    df = standing_counts(_stream(spark, sf, "events"), "//purchase/props", late="3650 days")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/{number:06d}")
        newest.append(number)

    newest: list[int] = []
    df.writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", new_path(spark, "standing-checkpoint")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{folder}/{max(newest):06d}").select(F.date_format("window_start", "yyyy-MM-dd").alias("day"), "n").where("n > 0")


def _ingested(spark: SparkSession, sf: str) -> DataFrame:
    def make(df: DataFrame) -> Carrier:
        return Carrier("pages", df.select(F.lit("pages").alias("carrier"), F.lit(0).alias("section"), F.col("page_id").alias("ord"), F.col("page_id").alias("doc_id"), F.col("html").alias("content")), None, "html")

    path = new_path(spark, "ingest")
    ingest(_stream(spark, sf, "pages"), make, path, new_path(spark, "ingest-checkpoint")).awaitTermination()
    return ingested(spark, path, "pages").count("//ul//a", by="doc")


def _dedup(spark: SparkSession, sf: str) -> DataFrame:
    ev = _stream(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "3650 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type", "ts")
    return run_to_table(ev, spark, "append", "dedup").select("user_id", "event_type")


def _joined(spark: SparkSession, sf: str) -> DataFrame:
    ev = _stream(spark, sf, "events").where("event_type = 'purchase'").join(table(spark, sf, "customer").select("c_custkey", "c_mktsegment"), F.col("user_id") == F.col("c_custkey"))
    return run_to_table(ev.select("event_id", "c_mktsegment"), spark, "append", "joined").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "stream_standing_counts": lambda s, d: written(s, _standing(s, d), "standing-out"),
        "stream_ingest_pages": _ingested,
        "stream_dedup": _dedup,
        "stream_static_join": _joined,
        "batch_session_counts": lambda s, d: session_counts(table(s, d, "events")).groupBy("user_id").agg(F.sum("n").alias("n")),
    }


def oracle_sql() -> dict[str, str]:
    return {
        "stream_standing_counts": "SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS n FROM events WHERE event_type = 'purchase' GROUP BY 1",
        "stream_ingest_pages": "SELECT page_id AS doc_id, CAST(len(regexp_extract_all(html, '<a[ >]')) AS BIGINT) AS n FROM pages",
        "stream_dedup": "SELECT DISTINCT user_id, event_type FROM events",
        "stream_static_join": "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey WHERE event_type = 'purchase' GROUP BY 1",
        "batch_session_counts": "SELECT user_id, count(*) AS n FROM events GROUP BY 1",
    }
