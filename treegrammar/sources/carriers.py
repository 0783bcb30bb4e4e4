"""How the given tables become trees.

Every carrier gives records (carrier, section, ord, doc_id, content): markup of one document, or, for ``market``, one
record of a giant document. A section is a child list of the giant document's spine; its records stand in the order of ``ord``.
Other carriers have a single section 0 without a spine, and each record is a document of its own.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

SUPPLIER_ORD = 1 << 40


@dataclass
class Spine:
    """An element of the top of a giant document; a section number marks the list that the records of a section form."""

    name: str
    children: list[Spine] = field(default_factory=list)
    section: int | None = None


@dataclass
class Carrier:
    name: str
    records: DataFrame
    spine: Spine | None = None
    policy: str = "strict"
    costly: bool = False  # whether the records come out of joins or groups, so that they are written once before they are cut into shards


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def esc(c: Column) -> Column:
    """Text as it stands in markup, or in a quoted attribute value."""
    c = F.coalesce(c.cast("string"), F.lit(""))
    for a, b in (("&", "&amp;"), ("<", "&lt;"), (">", "&gt;"), ('"', "&quot;")):
        c = F.replace(c, F.lit(a), F.lit(b))
    return c


def fmt_num(c: Column) -> Column:
    """The one text form of doubles: two places, rounded half up."""
    return F.round(c.cast("double"), 2).cast("decimal(18,2)").cast("string")


def fmt_time(c: Column) -> Column:
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss")


def el(name: str, *content: Column, attrs: Column | None = None) -> Column:
    head = F.lit(f"<{name}>") if attrs is None else F.concat(F.lit(f"<{name}"), attrs, F.lit(">"))
    return F.concat(head, *content, F.lit(f"</{name}>"))


def attr(name: str, value: Column) -> Column:
    return F.concat(F.lit(f' {name}="'), esc(value), F.lit('"'))


def joined(array: Column) -> Column:
    return F.array_join(array, "")


def ordered(keys: list[str], value: Column) -> Column:
    """The values of a group in the order of keys, one after another."""
    return joined(F.transform(F.array_sort(F.collect_list(F.struct(*keys, value.alias("xml")))), lambda s: s["xml"]))


def _docs(name: str, df: DataFrame, doc_id: Column, content: Column, policy: str = "strict", costly: bool = False) -> Carrier:
    d = doc_id.cast("long")
    return Carrier(name, df.select(F.lit(name).alias("carrier"), F.lit(0).alias("section"), d.alias("ord"), d.alias("doc_id"), content.alias("content")), None, policy, costly)


def pages(spark: SparkSession, sf_dir: str) -> Carrier:
    return _docs("pages", table(spark, sf_dir, "pages"), F.col("page_id"), F.col("html"), "html")


def threads(spark: SparkSession, sf_dir: str) -> Carrier:
    turns = table(spark, sf_dir, "conversations")
    say = lambda line: el("say", esc(line), joined(F.transform(F.regexp_extract_all(line, F.lit("([A-Za-z]{10,})"), F.lit(1)), lambda w: el("kw", w))))
    turns = turns.select("conv_id", "turn", F.concat(F.lit("<turn"), attr("role", F.col("role")), F.lit(">"), joined(F.transform(F.split("text", "\n"), say))).alias("xml"))
    nested = F.array_sort(F.collect_list(F.struct("turn", "xml")))
    per = turns.groupBy("conv_id").agg(nested.alias("t"))
    body = F.concat(F.array_join(F.transform("t", lambda s: s["xml"]), "<reply>"), F.repeat(F.lit("</turn></reply>"), F.size("t") - 1), F.lit("</turn>"))
    return _docs("threads", per, F.col("conv_id"), el("thread", body, attrs=attr("id", F.col("conv_id"))), costly=True)


def prose(spark: SparkSession, sf_dir: str) -> Carrier:
    docs = table(spark, sf_dir, "documents")
    word = lambda w: F.concat(F.lit("<w"), F.least(F.length(w), F.lit(20)).cast("string"), F.lit(">"), esc(w), F.lit("</w"), F.least(F.length(w), F.lit(20)).cast("string"), F.lit(">"))
    words = lambda s: joined(F.transform(F.filter(F.split(s, "\\s+"), lambda w: w != ""), word))
    para = lambda line: el("para", joined(F.transform(F.split(line, "(?<=\\.) "), lambda s: el("sent", words(s)))))
    return _docs("prose", docs, F.col("doc_id"), el("doc", joined(F.transform(F.split(F.coalesce("text", F.lit("")), "\n"), para)), attrs=F.concat(attr("lang", F.col("lang")), attr("source", F.col("source")))))


def log(spark: SparkSession, sf_dir: str) -> Carrier:
    return log_of(table(spark, sf_dir, "events"))


def event_xml() -> Column:
    props = F.map_entries(F.from_json("props", T.MapType(T.StringType(), T.StringType())))
    entries = joined(F.transform(F.array_sort(props), lambda e: F.concat(F.lit("<"), e["key"], F.lit(">"), esc(e["value"]), F.lit("</"), e["key"], F.lit(">"))))
    inner = F.concat(el("value", fmt_num(F.col("value"))), el("props", F.coalesce(entries, F.lit(""))))
    return F.concat(F.lit("<"), F.col("event_type"), attr("id", F.col("event_id")), F.lit(">"), inner, F.lit("</"), F.col("event_type"), F.lit(">"))


def log_of(events: DataFrame) -> Carrier:
    one = events.select("user_id", F.date_format("ts", "yyyy-MM-dd").alias("day"), "ts", "event_id", event_xml().alias("xml"))
    days = one.groupBy("user_id", "day").agg(ordered(["ts", "event_id"], F.col("xml")).alias("xml"))
    days = days.select("user_id", "day", el("day", F.col("xml"), attrs=attr("date", F.col("day"))).alias("xml"))
    users = days.groupBy("user_id").agg(ordered(["day"], F.col("xml")).alias("xml"))
    return _docs("log", users, F.col("user_id"), el("user", F.col("xml"), attrs=attr("id", F.col("user_id"))), costly=True)


def vectors(spark: SparkSession, sf_dir: str) -> Carrier:
    v = table(spark, sf_dir, "embeddings")
    dims = joined(F.transform("embedding", lambda x: el("dim", F.floor(x.cast("double") * 10000).cast("string"))))
    return _docs("vectors", v, F.col("vec_id"), el("vec", dims, attrs=attr("label", F.col("label"))))


LINE_ORDER = ["l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]


def market(spark: SparkSession, sf_dir: str) -> Carrier:
    """One giant auction-like document over the star schema."""
    t = lambda n: table(spark, sf_dir, n)
    orders, lines = t("orders"), t("lineitem")
    urgent = F.col("o_orderpriority").isin("1-URGENT", "2-HIGH")
    opt = lambda cond, c: F.when(cond, c).otherwise(F.lit(""))
    inner = opt(F.col("l_returnflag") == "R", el("list", el("listitem", el("text", esc(fmt_time(F.col("l_shipdate"))), el("keyword", esc(F.col("l_linestatus")))))))
    item = el("listitem", el("text", fmt_num(F.col("l_quantity")), opt(F.col("l_discount") >= 0.08, el("keyword", fmt_num(F.col("l_discount"))))), inner)
    per = lines.groupBy("l_orderkey").agg(F.count("*").alias("n_lines"), ordered(LINE_ORDER, item).alias("items"))
    sales = orders.join(per, orders["o_orderkey"] == per["l_orderkey"], "left")
    short = el("text", esc(fmt_time(F.col("o_orderdate"))), opt(urgent, el("keyword", esc(F.col("o_orderpriority")))))
    note = el("annotation", el("description", F.when(F.coalesce("n_lines", F.lit(0)) <= 2, short).otherwise(el("list", F.col("items")))))
    closed = F.col("o_orderstatus") == "F"
    ids = attr("id", F.col("o_orderkey"))
    sale = F.when(closed, el("closed_sale", el("price", fmt_num(F.col("o_totalprice"))), note, attrs=ids)).otherwise(el("open_sale", note, attrs=ids))

    regions = [(r["r_regionkey"], r["r_name"]) for r in t("region").orderBy("r_regionkey").collect()]  # a dimension of a handful of rows
    n = len(regions)
    number = F.coalesce(*[F.when(F.col("n_regionkey") == k, F.lit(i)) for i, (k, _) in enumerate(regions)], F.lit(None).cast("int"))
    home = t("nation").select("n_nationkey", number.alias("section"))

    purchase = el("purchase", el("note", esc(F.col("o_orderstatus")), opt(urgent, el("keyword", esc(F.col("o_orderpriority"))))), attrs=ids)
    baskets = orders.groupBy("o_custkey").agg(ordered(["o_orderkey"], purchase).alias("basket"))
    cust = t("customer").join(baskets, F.col("c_custkey") == F.col("o_custkey"), "left").join(F.broadcast(home), F.col("c_nationkey") == F.col("n_nationkey"))  # nations: a handful of rows
    shopper = el("shopper", el("name", esc(F.col("c_name"))), opt(F.col("basket").isNotNull(), el("basket", F.col("basket"))), attrs=F.concat(attr("id", F.col("c_custkey")), attr("segment", F.col("c_mktsegment"))))
    shops = t("supplier").join(F.broadcast(home), F.col("s_nationkey") == F.col("n_nationkey"))
    shop = el("shop", el("name", esc(F.col("s_name"))), attrs=attr("id", F.col("s_suppkey")))

    parts = t("part").groupBy("p_brand", "p_type").agg(ordered(["p_partkey"], el("part", el("name", esc(F.col("p_name"))), attrs=attr("id", F.col("p_partkey")))).alias("xml"))
    ordinal = F.row_number().over(Window.orderBy("p_brand", "p_type"))  # a few hundred kinds at any size
    parts = parts.withColumn("k", ordinal)

    def rec(df: DataFrame, section: Column, ord_: Column, xml: Column) -> DataFrame:
        return df.select(F.lit("market").alias("carrier"), section.cast("int").alias("section"), ord_.cast("long").alias("ord"), F.lit(0).cast("long").alias("doc_id"), xml.alias("content"))

    records = (
        rec(cust, F.col("section"), F.col("c_custkey"), shopper)
        .unionAll(rec(shops, F.col("section"), F.col("s_suppkey") + SUPPLIER_ORD, shop))
        .unionAll(rec(parts, F.lit(n), F.col("k"), el("category", F.col("xml"), attrs=attr("id", F.col("k")))))
        .unionAll(rec(sales, F.when(closed, n + 2).otherwise(n + 1), F.col("o_orderkey"), sale))
    )
    spine = Spine("site", [
        Spine("regions", [Spine(name.replace(" ", "_").lower(), section=i) for i, (_, name) in enumerate(regions)]),
        Spine("categories", section=n), Spine("open_sales", section=n + 1), Spine("closed_sales", section=n + 2),
    ])
    return Carrier("market", records, spine, costly=True)


CARRIERS = {"market": market, "threads": threads, "pages": pages, "prose": prose, "log": log, "vectors": vectors}


def carrier(spark: SparkSession, name: str, sf_dir: str) -> Carrier:
    return CARRIERS[name](spark, sf_dir)
