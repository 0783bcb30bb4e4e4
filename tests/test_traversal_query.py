import json

import duckdb
import numpy as np

from treegrammar.baselines.trees import structures
from treegrammar.grammar.compress import COMPRESSORS
from treegrammar.measure import shard_stats
from treegrammar.queries import label_trees, queries
from treegrammar.sources.carriers import log

SF = "/root/testdata/sf0.001"


def test_structures_of_every_document(spark):
    """No document of the log is left out."""
    documents = log(spark, SF).records.count()
    got = queries()["traversal_structures"](spark, SF).collect()
    assert documents > 8 and len(got) == 7
    assert all(r["documents"] == documents and r["orders_agree"] for r in got)


def test_equal_trees_are_worked_out_once_and_count_each(spark, tmp_path):
    """Users with the events of another one add documents, bytes and visits, but no tree."""
    small, twice = tmp_path / "small", tmp_path / "twice"
    for path, copies in ((small, 1), (twice, 2)):
        path.mkdir()
        users = f"SELECT e.* REPLACE (user_id + 1000000 * i AS user_id) FROM '{SF}/events.parquet' e, range({copies}) r(i) WHERE user_id < 6"
        duckdb.sql(f"COPY ({users}) TO '{path}/events.parquet' (FORMAT parquet)")
    one, two = ({r["structure"]: r for r in queries()["traversal_structures"](spark, str(p)).collect()} for p in (small, twice))
    assert len(one) == 7 and all(two[k][c] == 2 * one[k][c] > 0 for k in one for c in ("documents", "bytes", "visited"))
    trees = {p: label_trees(log(spark, str(p)).records, 3).collect() for p in (small, twice)}
    assert len(trees[small]) == len(trees[twice]) and sum(r["n"] for r in trees[twice]) == 2 * sum(r["n"] for r in trees[small]) == two["pairs"]["documents"]
    # The bytes are those of the grammars made one by one.
    events, names = np.frombuffer(trees[small][0]["events"], np.int32), [tuple(x) for x in json.loads(trees[small][0]["names"])]
    for name, (_, _, size) in structures(events, names).items():
        if name in COMPRESSORS:
            s = shard_stats(COMPRESSORS[name](names, events, np.array([0, len(events)])))
            assert size == int(s["rules_bytes"] + s["tag_bytes"] + s["ex_bytes"])
