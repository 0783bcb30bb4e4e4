"""The experiment workloads on the given tables: carrier, path, and the same answer in SQL over the base tables."""

from __future__ import annotations

from treegrammar.shared import new_path

ORDERS = """
o AS (SELECT o_orderkey, o_custkey, o_orderstatus AS s, o_totalprice, coalesce(c.n, 0) AS n, o_orderpriority IN ('1-URGENT', '2-HIGH') AS u
      FROM orders LEFT JOIN (SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY 1) c ON o_orderkey = l_orderkey),
l AS (SELECT o_orderkey, s, l_discount >= 0.08 AS d, l_returnflag = 'R' AS r FROM lineitem JOIN o ON l_orderkey = o_orderkey WHERE n > 2)
"""


def _one(expr: str) -> str:
    return f"WITH {ORDERS} SELECT CAST(({expr}) AS BIGINT) AS n"


_Q07 = "SELECT coalesce(sum(d::INT + r::INT), 0) FROM l"
_Q08 = "SELECT count(*) FROM o WHERE u"
_X1 = "SELECT count(*) FROM o WHERE s = 'F' AND n <= 2 AND u"
_X2 = f"({_X1}) + (SELECT coalesce(sum(d::INT + r::INT), 0) FROM l WHERE s = 'F')"
_Q3 = "SELECT count(*) FROM o WHERE n <= 2"
_LEVELS = [
    "1", "4", "(SELECT count(*) FROM region) + (SELECT count(DISTINCT (p_brand, p_type)) FROM part) + (SELECT count(*) FROM o)",
    "(SELECT count(*) FROM customer) + (SELECT count(*) FROM supplier) + (SELECT count(*) FROM part) + (SELECT count(*) FROM o) + (SELECT count(*) FROM o WHERE s = 'F')",
    "(SELECT count(*) FROM customer) + (SELECT count(DISTINCT o_custkey) FROM o) + (SELECT count(*) FROM supplier) + (SELECT count(*) FROM part) + (SELECT count(*) FROM o)",
    "2 * (SELECT count(*) FROM o)", "(SELECT count(*) FROM o) + (SELECT count(*) FROM o WHERE u AND n <= 2) + (SELECT count(*) FROM l)",
    "(SELECT count(*) FROM o WHERE u) + (SELECT count(*) FROM l) + (SELECT count(*) FROM l WHERE r)", "(SELECT count(*) FROM l WHERE d) + (SELECT count(*) FROM l WHERE r)",
    "(SELECT count(*) FROM l WHERE r)", "(SELECT count(*) FROM l WHERE r)",
]


def _deep(level: int) -> str:
    return "SELECT " + " + ".join(f"({e})" for e in _LEVELS[level:])


_LINES = "/site/closed_sales/closed_sale/annotation/description/list/listitem"
#: name -> path, SQL; counts on the giant document.
MARKET = {
    "q01": ("/site/regions", _one("SELECT 1")),
    "q02": ("/site/closed_sales", _one("SELECT 1")),
    "q03": ("/site/regions/europe/shopper/basket/purchase/note/keyword", _one("SELECT count(*) FROM o JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE u AND r_name = 'EUROPE'")),
    "q04": (_LINES, _one("SELECT count(*) FROM l WHERE s = 'F'")),
    "q05": (_LINES + "/list/listitem/*//keyword", _one("SELECT count(*) FROM l WHERE s = 'F' AND r")),
    "q06": ("/site/regions/*/shopper", _one("SELECT count(*) FROM customer")),
    "q06_any": ("/site/regions/*/*", _one("(SELECT count(*) FROM customer) + (SELECT count(*) FROM supplier)")),
    "q07": ("//listitem//keyword", _one(_Q07)),
    "q08": ("/site/regions/*/shopper//keyword", _one(_Q08)),
    "q13": ("//*", _one(_deep(0))),
    "q14": ("//*//*", _one(_deep(1))),
    "q15": ("//*//*//*//*", _one(_deep(3))),
    "q16": ("//*//*//*//*//*//*//*//*", _one(_deep(7))),
    "x1": ("/site/closed_sales/closed_sale/annotation/description/text/keyword", _one(_X1)),
    "x2": ("//closed_sale//keyword", _one(_X2)),
    "x3": ("/site/closed_sales/closed_sale//keyword", _one(_X2)),
    "simple_q1": ("//site/categories/category", _one("SELECT count(DISTINCT (p_brand, p_type)) FROM part")),
    "simple_q2": ("//open_sales/open_sale/annotation", _one("SELECT count(*) FROM o WHERE s IN ('O', 'P')")),
    "simple_q3": ("//description/text/text()", _one(_Q3)),
    "simple_q4": ("//text/text()", _one(f"({_Q3}) + (SELECT count(*) FROM l) + (SELECT count(*) FROM l WHERE r)")),
    "label_category": ("//category", _one("SELECT count(DISTINCT (p_brand, p_type)) FROM part")),
    "label_price": ("//price", _one("SELECT count(*) FROM o WHERE s = 'F'")),
    "label_keyword": ("//keyword", _one(f"({_Q08}) + (SELECT count(*) FROM o WHERE u AND n <= 2) + ({_Q07})")),
    "label_attrs": ("//@*", _one("2 * (SELECT count(*) FROM customer) + (SELECT count(*) FROM supplier) + 2 * (SELECT count(*) FROM o) + (SELECT count(*) FROM part) + (SELECT count(DISTINCT (p_brand, p_type)) FROM part)")),
    "fsib_listitem": ("//listitem/following-sibling::listitem", _one("SELECT coalesce(sum(n - 1), 0) FROM o WHERE n > 2")),
}

_SAYS = "SELECT conv_id, turn, unnest(string_split(text, chr(10))) AS line FROM conversations"
_KW = "len(regexp_extract_all(text, '[A-Za-z]{10,}'))"


def _tags(*names: str) -> str:
    return " + ".join(f"len(regexp_extract_all(html, '<{n}[ >]'))" for n in names)


#: name -> carrier, path, SQL of (doc_id, n).
DOCUMENTS = {
    "threads_turn": ("threads", "//turn", "SELECT conv_id AS doc_id, count(*) AS n FROM conversations GROUP BY 1"),
    "threads_nested_turn": ("threads", "//turn//turn", "SELECT conv_id AS doc_id, count(*) FILTER (turn > 0) AS n FROM conversations GROUP BY 1"),
    "threads_kw": ("threads", "//kw", f"SELECT conv_id AS doc_id, CAST(sum({_KW}) AS BIGINT) AS n FROM conversations GROUP BY 1"),
    "threads_reply_kw": ("threads", "//reply//kw", f"SELECT conv_id AS doc_id, CAST(coalesce(sum({_KW}) FILTER (turn > 0), 0) AS BIGINT) AS n FROM conversations GROUP BY 1"),
    "threads_fsib_say": ("threads", "//say/following-sibling::say", "SELECT conv_id AS doc_id, CAST(sum(len(string_split(text, chr(10))) - 1) AS BIGINT) AS n FROM conversations GROUP BY 1"),
    "pages_a": ("pages", "//a", f"SELECT page_id AS doc_id, CAST({_tags('a')} AS BIGINT) AS n FROM pages"),
    "pages_p": ("pages", "//p", f"SELECT page_id AS doc_id, CAST({_tags('p')} AS BIGINT) AS n FROM pages"),
    "pages_li": ("pages", "//li", f"SELECT page_id AS doc_id, CAST({_tags('li')} AS BIGINT) AS n FROM pages"),
    "pages_ul_a": ("pages", "//ul//a", f"SELECT page_id AS doc_id, CAST({_tags('a')} AS BIGINT) AS n FROM pages"),
    "pages_href": ("pages", "//@href", f"SELECT page_id AS doc_id, CAST({_tags('a')} AS BIGINT) AS n FROM pages"),
    "pages_p_b": ("pages", "//p/b", f"SELECT page_id AS doc_id, CAST({_tags('b')} AS BIGINT) AS n FROM pages"),
    "pages_p_p": ("pages", "//p//p", "SELECT page_id AS doc_id, CAST(0 AS BIGINT) AS n FROM pages"),
    "log_day": ("log", "//day", "SELECT user_id AS doc_id, count(DISTINCT CAST(ts AS DATE)) AS n FROM events GROUP BY 1"),
    **{f"log_{t}": ("log", f"//{t}", f"SELECT user_id AS doc_id, count(*) FILTER (event_type = '{t}') AS n FROM events GROUP BY 1") for t in ("click", "error", "purchase", "signup", "view")},
    "vectors_dim": ("vectors", "//dim", "SELECT vec_id AS doc_id, CAST(len(embedding) AS BIGINT) AS n FROM embeddings"),
    "vectors_fsib_dim": ("vectors", "//dim/following-sibling::dim", "SELECT vec_id AS doc_id, CAST(len(embedding) - 1 AS BIGINT) AS n FROM embeddings"),
    "prose_para": ("prose", "//para", "SELECT doc_id, CAST(len(string_split(text, chr(10))) AS BIGINT) AS n FROM documents"),
    "prose_w5": ("prose", "//w5", "SELECT doc_id, CAST(len(list_filter(regexp_split_to_array(text, '[ \\t\\n\\x0B\\f\\r]+'), lambda w: length(w) = 5)) AS BIGINT) AS n FROM documents"),
    "prose_words": ("prose", "//sent/*", "SELECT doc_id, CAST(len(list_filter(regexp_split_to_array(text, '[ \\t\\n\\x0B\\f\\r]+'), lambda w: w <> '')) AS BIGINT) AS n FROM documents"),
}

_INDEXES: dict[tuple, object] = {}


def index(spark, sf_dir: str, name: str, compressor: str = "pairs", max_rank: int = 2, shard_nodes: int | None = None, dictionary: int = 0):
    """The index of a carrier, built once for each application, tables and variant."""
    from treegrammar.operators.index import SHARD_NODES, TreeIndex
    from treegrammar.sources.carriers import carrier

    key = (spark.sparkContext.applicationId, sf_dir, name, compressor, max_rank, shard_nodes, dictionary)
    if key not in _INDEXES:
        path = new_path(spark, f"index-{name}")
        _INDEXES[key] = TreeIndex.build(spark, carrier(spark, name, sf_dir), path, compressor, max_rank, shard_nodes or SHARD_NODES, dictionary)
    return _INDEXES[key]


_NODES: dict[tuple, str] = {}


def nodes(spark, sf_dir: str, name: str):
    """The node table of a carrier's index, decompressed and written once for each application: what the baselines read."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _NODES:
        path = new_path(spark, f"nodes-{name}")
        index(spark, sf_dir, name).nodes().write.parquet(path)
        _NODES[key] = path
    return spark.read.parquet(_NODES[key])
