"""The queries of the ten operators and, where SQL can express them, their oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treegrammar.llm import bpe, decontaminate, exact_dedup, html_extract, language, license_scan, sharding, simhash, toxicity, url_filter
from treegrammar.llm.holdout import held_out

TOKENIZER = "byte_bpe_50k.json"


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def tokenizer_text(path: str | None = None) -> str:
    """The text of a tokenizer file; by default the public byte-level one of the installed package."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path(TOKENIZER)
    return bpe.read_tokenizer(path)


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(spark, table(spark, sf_dir, "documents", "doc_id", "text"))


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan(table(spark, sf_dir, "documents", "doc_id", "text"))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_components(spark, table(spark, sf_dir, "documents", "doc_id", "text"))


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(spark, table(spark, sf_dir, "documents", "doc_id", "text", "lang", "source"))


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.overlaps(spark, table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text"))


def op6_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages", "page_id", "url", "html")
    return html_extract.extract(spark, pages, html_extract.fit(spark, pages))


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    model = language.fit(spark, docs)
    return language.predict(spark, docs, model).select("doc_id", held_out("doc_id").alias("held_out"), "lang_pred", "score")


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    model = toxicity.fit(spark, docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return toxicity.scores(spark, docs, model).select("doc_id", held_out("doc_id").alias("held_out"), "score", "predicted", "evidence")


def op9_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digests(table(spark, sf_dir, "documents", "doc_id", "text"), tokenizer_text())


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(spark, table(spark, sf_dir, "pages", "page_id", "url")).withColumn("purity", F.round("purity", 9))


OP1_SQL = """
WITH n AS (
  SELECT doc_id, coalesce(text, '') AS t, regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]', '', 'g') AS body FROM documents
), r AS (
  SELECT doc_id, body, row_number() OVER (PARTITION BY body ORDER BY length(t) DESC, doc_id) AS k, count(*) OVER (PARTITION BY body) AS group_size,
         first_value(doc_id) OVER (PARTITION BY body ORDER BY length(t) DESC, doc_id) AS keep_id
  FROM n
)
SELECT doc_id, keep_id, group_size, k = 1 AS kept, sha256(body) AS text_sha256 FROM r
"""

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def op2_sql() -> str:
    """Diagonal votes over the grams themselves instead of their hashes."""
    k = license_scan
    rows = []
    for number, (label, phrase) in enumerate([*k.BASE, *k.MORE], 1):
        w = phrase.split(" ")
        rows += [f"('{' '.join(w[a : a + k.GRAM])}', {number}, '{label}', {str(number <= len(k.BASE)).lower()}, {a}, {len(w) - k.GRAM + 1})" for a in range(len(w) - k.GRAM + 1)]
    return f"""
WITH t(gram, template, label, base, at_, grams) AS (VALUES {', '.join(rows)}),
d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
g AS (SELECT doc_id, unnest(range(0, len(w) - 2)) AS pos, unnest(list_transform(range(0, len(w) - 2), lambda i: w[i + 1] || ' ' || w[i + 2] || ' ' || w[i + 3])) AS gram FROM d),
v AS (SELECT doc_id, template, label, base, grams, pos - at_ AS diagonal, count(*) AS votes, min(pos) AS start, max(pos) AS stop FROM g JOIN t USING (gram) GROUP BY ALL),
s AS (SELECT *, sum(apart) OVER (PARTITION BY doc_id, template ORDER BY diagonal) AS span FROM (
  SELECT *, CASE WHEN diagonal - lag(diagonal) OVER (PARTITION BY doc_id, template ORDER BY diagonal) <= {k.NEAR} THEN 0 ELSE 1 END AS apart FROM v)),
m AS (SELECT doc_id, label, base, grams, sum(votes) AS votes, min(start) AS start, max(stop) + {k.GRAM - 1} AS stop, count(*) FILTER (base AND votes = grams) AS places,
        min(diagonal) FILTER (base AND votes = grams) AS first, max(diagonal) FILTER (base AND votes = grams) AS last FROM s GROUP BY doc_id, template, label, base, grams, span),
f AS (SELECT *, least(1.0, votes / grams) AS cover, places > 0 OR (least(1.0, votes / grams) >= CASE WHEN grams < {k.SHORT} THEN 1.0 ELSE {k.MIN_COVER} END AND stop - start + 1 <= {k.SLACK} * (grams + {k.GRAM - 1}) + {k.NEAR}) AS found FROM m)
SELECT d.doc_id, CAST(len(any_value(w)) AS BIGINT) AS n_words, CAST(coalesce(sum(places), 0) AS BIGINT) AS n_base, CAST(min(first) AS BIGINT) AS first_word, CAST(max(last) AS BIGINT) AS last_word,
  coalesce(string_agg(DISTINCT label, ',' ORDER BY label) FILTER (places > 0), '') AS base_labels, coalesce(string_agg(DISTINCT label, ',' ORDER BY label) FILTER (found), '') AS labels,
  CAST(coalesce(max(CASE WHEN places > 0 THEN 1.0 ELSE cover END) FILTER (found), 0.0) AS DOUBLE) AS score
FROM d LEFT JOIN f USING (doc_id) GROUP BY d.doc_id
"""


def op10_sql() -> str:
    """The rules, then the template tree level by level."""
    k = url_filter
    fits = [(f"((host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}'))", h + p, v) for h, p, v in sorted(k.RULES, key=lambda r: -len(r[0] + r[1]))]
    rule, said = (" ".join(f"WHEN {c} THEN '{x[n]}'" for c, *x in fits) for n in (0, 1))
    levels = []
    for i in range(k.DEPTH):
        levels.append(f"""
o{i} AS (SELECT *, CASE WHEN regexp_matches(seg[{i + 1}], '{k._IDENTIFIER}') THEN '*' ELSE seg[{i + 1}] END AS own FROM p{i}),
c{i} AS (SELECT host, prefix, own, sum(n) AS n, sum(labelled) AS labelled, sum(blocked) AS blocked, count(*) AS paths FROM o{i} WHERE own IS NOT NULL GROUP BY ALL),
a{i} AS (SELECT host, prefix, count(*) AS kinds, sum(n) AS all_n, sum(labelled) AS all_labelled, sum(blocked) AS all_blocked, count(*) FILTER (labelled > 0) AS told, sum(paths) AS all_paths, coalesce(sum(blocked / labelled) FILTER (labelled > 0), 0) AS bad FROM c{i} GROUP BY ALL),
n{i} AS (SELECT host, prefix, own, CASE WHEN own = '*' OR (kinds > {k.MANY} AND n < {k.RARE} * all_n) THEN '*'
    WHEN labelled > 0 AND all_labelled > labelled AND abs(blocked / labelled - (all_blocked - blocked) / (all_labelled - labelled))
      <= {k.ALIKE} * sqrt(greatest(all_blocked / all_labelled * (1 - all_blocked / all_labelled), 0.01) * (1 / labelled + 1 / (all_labelled - labelled))) THEN '~' ELSE own END AS name, told, bad, all_paths FROM c{i} JOIN a{i} USING (host, prefix)),
p{i + 1} AS (SELECT o.host, o.path, o.n, o.labelled, o.blocked, o.seg, o.lone OR coalesce(all_paths = 1, TRUE) AS lone, CASE WHEN name IS NULL OR o.lone THEN o.prior ELSE (bad + {k.PRIOR} * o.prior) / (told + {k.PRIOR}) END AS prior, CASE WHEN name IS NULL THEN o.prefix ELSE o.prefix || '/' || name END AS prefix FROM o{i} o LEFT JOIN n{i} USING (host, prefix, own)),""")
    return f"""
WITH u AS (SELECT page_id, translate(regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)', 1), '{_UPPER}', '{_LOWER}') AS host, regexp_extract(coalesce(url, ''), '(?s)^.*?://[^/?#]*([^?#]*)', 1) AS path FROM pages),
j AS (SELECT *, CASE {rule} END AS rule, CASE {said} END AS listed FROM u),
q AS (SELECT host, path, count(*) AS n, count(listed) AS labelled, count(*) FILTER (listed = 'block') AS blocked, string_split(regexp_replace(path, '^/', ''), '/') AS s FROM j GROUP BY host, path),
p0 AS (SELECT host, path, n, labelled, blocked, CASE WHEN len(s) > {k.DEPTH} THEN list_append(s[1:{k.DEPTH - 1}], array_to_string(s[{k.DEPTH}:], '/')) ELSE s END AS seg, CAST({k.CENTRE} AS DOUBLE) AS prior, FALSE AS lone, '' AS prefix FROM q),
{''.join(levels)}
w AS (SELECT host, prefix AS template, (sum(blocked) + {k.PRIOR} * avg(prior)) / (sum(labelled) + {k.PRIOR}) AS purity FROM p{k.DEPTH} GROUP BY ALL)
SELECT page_id, j.host, j.path, rule, coalesce(listed, CASE WHEN round(purity, 9) >= {k.REJECT} THEN 'block' ELSE 'allow' END) AS verdict, template, round(CAST(purity AS DOUBLE), 9) AS purity
FROM j JOIN (SELECT host, path, prefix AS template FROM p{k.DEPTH}) x USING (host, path) JOIN w USING (host, template)
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_exact_dedup": op1_exact_dedup,
        "op2_license_scan": op2_license_scan,
        "op3_simhash": op3_simhash,
        "op4_sharding": op4_sharding,
        "op5_decontaminate": op5_decontaminate,
        "op6_html_extract": op6_html_extract,
        "op7_language": op7_language,
        "op8_toxicity": op8_toxicity,
        "op9_bpe": op9_bpe,
        "op10_url_filter": op10_url_filter,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_exact_dedup": OP1_SQL, "op2_license_scan": op2_sql(), "op10_url_filter": op10_sql()}
