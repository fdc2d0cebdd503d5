"""One query for each operator of this subpackage, over whole tables and with production parameters."""

from __future__ import annotations

import secrets

from pyspark.sql import DataFrame, SparkSession

from . import decontam, exact_dedup, html_main, langid, licenses, ngram_join, packing, pii, simple8b, token_rollup
from .common import documents


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A row for each paragraph with a licence notice."""
    return licenses.scan(documents(spark, sf_dir))


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A row for each document and benchmark item that it holds."""
    return decontam.contaminated(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(documents(spark, sf_dir))


def op4_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.join(documents(spark, sf_dir))


def op5_html_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_main.extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def op6_token_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals after a load, a takedown and a recount."""
    return token_rollup.maintained(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op7_simple8b_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simple8b.round_trip(documents(spark, sf_dir))


def op8_sum_of_squares_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir))


def op9_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its rewritten text. The key is the session's ``spark.rectjoin.pii.key``, or a new one for each run."""
    key = spark.conf.get("spark.rectjoin.pii.key", None)
    return pii.replace(documents(spark, sf_dir).select("doc_id", "text"), key.encode() if key else secrets.token_bytes(32))


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.combine(documents(spark, sf_dir))


QUERIES = {f.__name__: f for f in (op1_license_scan, op2_decontaminate, op3_language_id, op4_ngram_jaccard_join, op5_html_main_text, op6_token_rollup, op7_simple8b_output, op8_sum_of_squares_packing, op9_pii_surrogates, op10_exact_dedup)}

_WORDS = r"regexp_extract_all(coalesce({text}, ''), '[^\x20\x09-\x0D]+')"

ORACLES = {
    "op4_ngram_jaccard_join": rf"""
WITH RECURSIVE words AS (
  SELECT doc_id, {_WORDS.format(text="translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')")} AS w FROM documents
), sets AS (
  SELECT doc_id, CASE WHEN len(w) >= 5 THEN list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')))
                      WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS s FROM words
), members AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM sets),
links AS (
  SELECT a.doc_id AS x, b.doc_id AS y FROM members a JOIN members b ON a.g = b.g AND a.doc_id <> b.doc_id
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 75 * (a.n + b.n - count(*))
), reach(node, root) AS (
  SELECT doc_id, doc_id FROM documents UNION SELECT l.y, r.root FROM reach r JOIN links l ON l.x = r.node
)
SELECT s.doc_id, CAST(len(s.s) AS BIGINT) AS n_shingles, r.component_id
FROM sets s JOIN (SELECT node, min(root) AS component_id FROM reach GROUP BY node) r ON r.node = s.doc_id""",
    "op10_exact_dedup": """
WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
g AS (SELECT text, max(doc_id) AS keep_id, count(*) AS group_size FROM t GROUP BY text)
SELECT t.doc_id, g.keep_id, CAST(g.group_size AS BIGINT) AS group_size, t.doc_id = g.keep_id AS kept, sha256(t.text) AS text_sha256
FROM t JOIN g ON t.text = g.text""",
}
