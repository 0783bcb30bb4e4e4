"""A Python data source over an index on a file system that the workers see: one partition a file, filters on doc_id pushed down.

    register(spark)
    spark.read.format("treegrammar_index").option("path", dir).option("query", "//a").load()      # doc_id, n
    df.write.format("treegrammar_index").option("path", dir).save()                              # (doc_id, xml) as .xml files
"""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterator
from xml.sax.saxutils import quoteattr

import pyarrow.parquet as pq
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, EqualTo, Filter, InputPartition, WriterCommitMessage


def register(spark) -> None:
    """Make the source known, and let Spark hand filters down to Python sources (a setting of the running session)."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(TreeGrammarSource)


class Part(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)
        self.path = path


class Written(WriterCommitMessage):
    def __init__(self, path: str):
        self.path = path


class TreeGrammarSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "treegrammar_index"

    def schema(self) -> str:
        return "doc_id long, n long"

    def reader(self, schema) -> DataSourceReader:
        return IndexReader(self.options)

    def writer(self, schema, overwrite: bool) -> DataSourceWriter:
        return XmlWriter(self.options)


def _local(path: str) -> str:
    return path.removeprefix("file://").removeprefix("file:")


class IndexReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.query, self.doc = _local(options["path"]), options.get("query", "//*"), None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("doc_id",):
                self.doc = f.value
            else:
                yield f

    def partitions(self) -> list[Part]:
        return [Part(os.path.join(d, x)) for d, _, names in os.walk(self.path) for x in sorted(names) if x.endswith(".parquet")]

    def read(self, partition: Part) -> Iterator[tuple]:
        from treegrammar.operators.index import CORE, load_shard
        from treegrammar.views.rulewise import Run
        from treegrammar.xpath.automaton import compile_path

        a = compile_path(self.query)
        for row in pq.read_table(partition.path, columns=CORE).to_pylist():
            if self.doc is not None and self.doc not in row["doc_ids"]:
                continue
            for d, n in zip(row["doc_ids"], Run(load_shard(row), a).eager_count()[0].tolist(), strict=True):
                if self.doc is None or d == self.doc:
                    yield d, n


class XmlWriter(DataSourceWriter):
    """Writes (doc_id, xml) rows to one file a task; a failed task leaves no file under the final name."""

    def __init__(self, options):
        self.path = _local(options["path"])

    def write(self, rows: Iterator) -> Written:
        os.makedirs(self.path, exist_ok=True)
        name = os.path.join(self.path, f"{uuid.uuid4().hex}.xml")
        with open(name + ".tmp", "w", encoding="utf-8") as f:
            f.write("<documents>\n")
            for r in rows:
                f.write(f"<document id={quoteattr(str(r['doc_id']))}>{r['xml']}</document>\n")
            f.write("</documents>\n")
        return Written(name)

    def commit(self, messages: list[Written | None]) -> None:
        for m in messages:
            if m is not None:
                os.rename(m.path + ".tmp", m.path)

    def abort(self, messages: list[Written | None]) -> None:
        for m in messages:
            if m is not None and os.path.exists(m.path + ".tmp"):
                os.remove(m.path + ".tmp")
