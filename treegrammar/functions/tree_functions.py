"""Functions for SQL and DataFrames: packed rules, markup tokens, path counts on markup, ordered composition, and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from treegrammar.sources.carriers import fmt_num, fmt_time
from treegrammar.sources.markup import forest_of, node_table
from treegrammar.xpath.automaton import compile_path

_INT, _STR = T.IntegerType(), T.StringType()


def _row(**fields: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in fields.items()])


# Packed rules: 28 bits for the outer symbol, 28 for the inner one, 4 for the hole, 4 for the rank.


def pack_rule(outer: Column, hole: Column, inner: Column, rank: Column) -> Column:
    wide = lambda c: c.cast("long")
    return F.shiftleft(wide(outer), 36).bitwiseOR(F.shiftleft(wide(inner), 8)).bitwiseOR(F.shiftleft(wide(hole), 4)).bitwiseOR(wide(rank))


def rule_outer(rule: Column) -> Column:
    return F.shiftrightunsigned(rule, 36)


def rule_inner(rule: Column) -> Column:
    return F.shiftrightunsigned(rule, 8).bitwiseAND((1 << 28) - 1)


def rule_hole(rule: Column) -> Column:
    return F.shiftrightunsigned(rule, 4).bitwiseAND(15)


def rule_rank(rule: Column) -> Column:
    return rule.bitwiseAND(15)


@F.pandas_udf(T.ArrayType(T.StructType([T.StructField("kind", T.IntegerType()), T.StructField("label", T.StringType())])))
def markup_tokens(html: pd.Series) -> pd.Series:
    """The parenthesis stream of each page: kind -1 closes a node."""
    out = []
    for page in html:
        f = forest_of([(0, page)], "html")
        out.append([{"kind": f.names[e][0], "label": f.names[e][1]} if e >= 0 else {"kind": -1, "label": None} for e in f.events])
    return pd.Series(out)


@F.pandas_udf(T.LongType())
def xpath_count_html(html: pd.Series, path: pd.Series) -> pd.Series:
    """Nodes that a path selects in each page, read tolerantly; the path is compiled once a batch."""
    from treegrammar.grammar.compress import one_rule
    from treegrammar.views.rulewise import Run

    out = pd.Series(0, index=html.index, dtype="int64")
    for p in path.unique():
        at = html.index[path == p]
        f = forest_of([(0, html[i]) for i in at], "html")
        events, doc_start = f.arrays()
        out[at] = Run(one_rule(f.names, events, doc_start), compile_path(p)).eager_count()[0]
    return out


@F.pandas_udf(T.ArrayType(T.IntegerType()))
def behaviour_compose(ord_: pd.Series, out: pd.Series) -> float:  # a list; the hint marks one value a group
    """The composition, in the order of ord_, of maps from state to state given as arrays."""
    now = None
    for k in ord_.sort_values(kind="stable").index:
        step = list(out[k])
        now = step if now is None else [step[q] for q in now]
    return now or []


@F.udtf(returnType=_row(node=_INT, label=_STR, kind=_INT, parent=_INT, size=_INT, level=_INT, pre=_INT))
class Shred:
    """The node table of one page: SELECT * FROM shred(html), or a lateral join."""

    def eval(self, html: str) -> Iterator[tuple]:
        f = forest_of([(0, html)], "html")
        events, _ = f.arrays()
        t = node_table(events, [k for k, _ in f.names])
        for k, lab in enumerate(t["label"].tolist()):
            kind, name = f.names[lab]
            yield k, name, kind, int(t["parent"][k]), int(t["size"][k]), int(t["level"][k]), int(t["pre"][k])


@F.udtf(returnType=_row(node=_INT, pre=_INT, xml=_STR))
class XPathResults:
    """The nodes of one page that a path selects, with their markup: SELECT * FROM xpath_results(html, '//a')."""

    def eval(self, html: str, path: str) -> Iterator[tuple]:
        from treegrammar.grammar.compress import one_rule
        from treegrammar.views.chunkwise import Chunkwise, Renderer, subtree_ends
        from treegrammar.views.rulewise import Run

        f = forest_of([(0, html)], "html")
        events, doc_start = f.arrays()
        (tags, res), = Chunkwise(Run(one_rule(f.names, events, doc_start), compile_path(path))).serialize(f.texts, f.doc_texts)[0]
        if not res.shape[1]:
            return
        show = Renderer(f.names, f.texts)
        for b, e, pre, node, t in zip(res[0].tolist(), subtree_ends(tags, res[0]).tolist(), res[1].tolist(), res[2].tolist(), res[3].tolist(), strict=True):
            yield node, pre, show(tags, b, e, t)


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL."""
    spark.udf.register("markup_tokens", markup_tokens)
    spark.udf.register("xpath_count_html", xpath_count_html)
    spark.udtf.register("shred", Shred)
    spark.udtf.register("xpath_results", XPathResults)


__all__ = ["behaviour_compose", "fmt_num", "fmt_time", "markup_tokens", "pack_rule", "register", "rule_hole", "rule_inner", "rule_outer", "rule_rank", "xpath_count_html"]
