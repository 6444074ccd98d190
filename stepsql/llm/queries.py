"""One thin query for each operator, and the SQL of those that DuckDB can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import bpe, exact, html, langid, license, packing, quality, shard, simhash, topk
from .common import read


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license.scan(read(spark, sf_dir, "documents")).drop("spans")


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.dedup(read(spark, sf_dir, "documents"))


def op3_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    return quality.predict(docs, quality.fit(docs, read(spark, sf_dir, "labels")))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    return langid.predict(docs, langid.fit(docs))


def op6_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard.shard(read(spark, sf_dir, "documents"))


def op7_bpe_encode(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_documents(read(spark, sf_dir, "documents"), keep_ids=False)


def op4_simhash_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.components(read(spark, sf_dir, "documents"))


def op8_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = read(spark, sf_dir, "embeddings")
    return topk.top_k(vectors, vectors.where("vec_id % 50 = 0"))


def op9_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract(read(spark, sf_dir, "pages"))


def op10_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(read(spark, sf_dir, "documents"))


QUERIES = {
    f.__name__: f
    for f in (
        op1_license_scan, op2_exact_dedup, op3_quality_classifier, op4_simhash_near_dup, op5_language_id,
        op6_sharding, op7_bpe_encode, op8_exact_topk, op9_html_extraction, op10_best_fit_packing,
    )
}

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_FOLDED = f"translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}')"


def _license_sql() -> str:
    config = license.Config()
    rows = ", ".join(f"('{x} {y}', {t}, {p})" for x, y, t, p in license.template_rows(config))
    kinds = ", ".join(f"({n}, '{label}', {len(words) - 1}, {str(n < len(config.base)).lower()}, {need or '[]'}::INTEGER[][])" for n, (words, label, need) in enumerate(config.templates))
    return f"""
WITH texts AS (
  SELECT doc_id, row_number() OVER () AS row, regexp_extract_all({_FOLDED}, '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM documents),
templates(gram, template, position) AS (VALUES {rows}),
kinds(template, label, grams, base, need) AS (VALUES {kinds}),
places AS (SELECT row, unnest(range(len(w) - 1)) AS place, w FROM texts WHERE len(w) >= 2),
words AS (SELECT row, place, w[place + 1] || ' ' || w[place + 2] AS gram FROM places),
hits AS (SELECT row, template, place, position, place - position AS diagonal FROM words JOIN templates USING (gram)),
votes AS (SELECT row, template, diagonal, count(*) AS n FROM hits GROUP BY ALL),
based AS (SELECT row, label, diagonal AS first FROM votes JOIN kinds USING (template) WHERE base AND n = grams),
near AS (SELECT a.row, a.template, a.diagonal AS anchor, b.diagonal, b.n
  FROM votes a JOIN votes b ON a.row = b.row AND a.template = b.template AND b.diagonal BETWEEN a.diagonal AND a.diagonal + {config.slack}
  WHERE NOT (SELECT any_value(base) FROM kinds k WHERE k.template = a.template)),
chosen AS (
  SELECT n.row, n.template, anchor, position, arg_max(place, (n, -n_.diagonal)) AS place
  FROM (SELECT *, diagonal AS d FROM near) n JOIN hits n_ ON n_.row = n.row AND n_.template = n.template AND n_.diagonal = n.d GROUP BY ALL),
kept AS (SELECT * FROM chosen QUALIFY place > coalesce(max(place) OVER (PARTITION BY row, template, anchor ORDER BY position ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), -1)),
spans AS (SELECT row, template, anchor, list(position) AS positions, list(place) AS places, count(*) AS n FROM kept GROUP BY ALL),
verified AS (
  SELECT row, template, anchor, places, label, grams, n::DOUBLE / grams AS share FROM spans JOIN kinds USING (template)
  WHERE n >= {config.least} * grams AND len(list_filter(need, lambda held: NOT list_has_any(held, positions))) = 0),
claims AS (SELECT row, template, anchor, label, grams, share, unnest(places) AS place FROM verified),
judged AS (SELECT *, first_value(label) OVER (PARTITION BY row, place ORDER BY share DESC, grams DESC, label DESC) = label AS won FROM claims),
stands AS (SELECT row, template, anchor, label, share FROM judged GROUP BY row, template, anchor, label, share, grams HAVING count(*) FILTER (won) >= {config.least} * grams),
every AS (SELECT row, label, first, 1.0::DOUBLE AS share, true AS base FROM based UNION ALL SELECT row, label, anchor, share, false FROM stands)
SELECT t.doc_id, len(any_value(t.w))::BIGINT AS n_words, count(*) FILTER (base)::BIGINT AS n_base,
  min(first) FILTER (base)::BIGINT AS first_word, max(first) FILTER (base)::BIGINT AS last_word,
  coalesce(string_agg(DISTINCT label, ',' ORDER BY label) FILTER (base), '') AS base_labels,
  coalesce(string_agg(DISTINCT label, ',' ORDER BY label), '') AS labels, coalesce(max(share), 0.0)::DOUBLE AS score
FROM texts t LEFT JOIN every USING (row) GROUP BY t.row, t.doc_id"""


ORACLE_SQL = {
    "op1_license_scan": _license_sql(),
    "op2_exact_dedup": f"""
WITH n AS (SELECT doc_id, {_FOLDED} AS t FROM documents),
g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY t)
SELECT n.doc_id, g.keep_id, g.group_size, row_number() OVER (PARTITION BY n.t ORDER BY n.doc_id DESC NULLS LAST) = 1 AS kept, sha256(n.t) AS text_sha256 FROM n JOIN g USING (t)""",
    "op8_exact_topk": """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS q FROM embeddings),
pairs AS (
  SELECT a.vec_id AS query_id, b.vec_id, list_dot_product(a.q, b.q)::BIGINT AS score
  FROM v a JOIN v b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0),
ranked AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM pairs)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 5""",
}
