"""The operators' queries over the given tables, and the SQL of those that SQL can express."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import blocks, bpe, exact, jaccard, langid, mixing, quality, slices, urls, warc
from .common import split_mark

RULES = [("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block")]
#: The listed URLs are the canonical ones of pages whose host has one of these as its first label but www. and m.
LISTED_HOSTS = ("spam-farm", "cheap-pills")
#: Shares of tokens that the mixture is to have.
SHARES = {"good": 0.95, "low": 0.05, "toxic": 0.0}


def vocabulary() -> str:
    """The tokenizer's file; RAYFIT_BPE names another."""
    if path := os.environ.get("RAYFIT_BPE"):
        return path
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def digests(encoded: DataFrame) -> DataFrame:
    return encoded.select("doc_id", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op1_bpe(spark, sf_dir):
    return digests(bpe.encode(table(spark, sf_dir, "documents"), vocabulary()))


def op2_quality(spark, sf_dir):
    out = quality.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), ~split_mark("doc_id", 3, 1))
    return out.select("doc_id", split_mark("doc_id", 3, 1).alias("held_out"), "score", "predicted")


def op3_urls(spark, sf_dir):
    pages = table(spark, sf_dir, "pages")
    canon = urls.canonical(F.col("url"))
    listed = pages.select(canon.alias("canon")).filter(F.substring_index(F.substring_index("canon", "/", 1), ".", 1).isin(*LISTED_HOSTS)).distinct()
    return urls.judge(pages, RULES, listed)


def op4_warc(spark, sf_dir):
    return warc.read(warc.write(table(spark, sf_dir, "pages")))


def op5_html(spark, sf_dir):
    return blocks.extract(table(spark, sf_dir, "pages"))


def op6_topk(spark, sf_dir):
    return slices.search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op7_jaccard(spark, sf_dir):
    return jaccard.join(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id", "class_id")


def op8_language(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    held = split_mark("doc_id", 4, 2)
    return langid.label(docs, langid.fit(docs.filter(~held))).select("doc_id", held.alias("held_out"), "lang_pred", "score")


def domains(labels: DataFrame) -> DataFrame:
    """good, low or toxic for each labelled document."""
    name = F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "low")
    return labels.select("doc_id", name.alias("domain"))


def op9_mixing(spark, sf_dir):
    return mixing.mix(table(spark, sf_dir, "documents"), domains(table(spark, sf_dir, "labels")), SHARES, "good")


def op10_dedup(spark, sf_dir):
    return exact.groups(table(spark, sf_dir, "documents"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_bpe, op2_quality, op3_urls, op4_warc, op5_html, op6_topk, op7_jaccard, op8_language, op9_mixing, op10_dedup)}


_SPLIT = """
WITH cut AS (SELECT page_id, url, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
parts AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
  regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM cut),
canon AS (SELECT *, regexp_replace(host, '^(www|m)\\.', '') || regexp_replace(path, '(\\.html)?/*$', '') AS canon FROM parts)"""

_RULES = ", ".join(f"('{h}', '{p}', '{v}')" for h, p, v in RULES)
_LISTED = ", ".join(f"'{h}'" for h in LISTED_HOSTS)


def oracle_sql() -> dict:
    return {
        "op3_urls": f"""{_SPLIT},
rules(h, p, v) AS (VALUES {_RULES}),
fit AS (SELECT page_id, arg_max(h || p, length(h || p)) AS rule, arg_max(v, length(h || p)) AS ruling
  FROM canon JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p) GROUP BY page_id),
listed AS (SELECT DISTINCT canon FROM canon WHERE split_part(split_part(canon, '/', 1), '.', 1) IN ({_LISTED}))
SELECT c.page_id, c.host, c.path, f.rule,
  coalesce(f.ruling, CASE WHEN l.canon IS NOT NULL THEN 'block' ELSE 'allow' END) AS verdict,
  (f.rule IS NULL AND l.canon IS NOT NULL) AS listed
FROM canon c LEFT JOIN fit f USING (page_id) LEFT JOIN listed l ON c.canon = l.canon""",
        "op4_warc": """
WITH p AS (SELECT page_id, coalesce(html, '') AS body FROM pages),
h AS (SELECT page_id, octet_length(encode(body)) AS payload_bytes, sha1(body) AS hex, min(page_id) OVER (PARTITION BY body) AS first FROM p)
SELECT page_id, payload_bytes, list_aggregate(list_transform(range(0, 8), lambda i: list_aggregate(list_transform([15, 10, 5, 0],
    lambda b: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST((('0x' || substr(hex, CAST(5 * i + 1 AS INTEGER), 5))::BIGINT >> b) & 31 AS INTEGER) + 1, 1)), 'string_agg', '')), 'string_agg', '') AS payload_digest,
  CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> first THEN first END AS refers_to FROM h""",
        "op6_topk": """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS v FROM embeddings),
s AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_dot_product(CAST(q.v AS DOUBLE[]), CAST(c.v AS DOUBLE[])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5""",
        "op10_dedup": """
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, sha256(coalesce(text, '')) AS text_sha256
FROM documents WINDOW w AS (PARTITION BY coalesce(text, ''))""",
        "op7_jaccard": r"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
  ELSE list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i : i + 4], ' '))) END AS s FROM w),
e AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM s),
l AS (SELECT x.doc_id AS a, y.doc_id AS b FROM e x JOIN e y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY x.doc_id, y.doc_id, x.n, y.n
  HAVING 100 * count(*) >= 75 * (x.n + y.n - count(*))),
r(a, b) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a),
c AS (SELECT a AS doc_id, min(b) AS component_id FROM r GROUP BY a),
k AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY CASE WHEN len(s) = 0 THEN CAST(doc_id AS VARCHAR) ELSE array_to_string(list_sort(s), '|') END) AS class_id FROM s)
SELECT s.doc_id, CAST(len(s.s) AS BIGINT) AS n_shingles, component_id, class_id FROM s JOIN c USING (doc_id) JOIN k USING (doc_id)""",
    }
