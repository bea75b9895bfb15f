"""Queries of the training-data operators, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from tolerant_gd.llm import decontaminate, host_reputation, iso_media, mincut_html, ppm_language, rule_ensemble, secret_scan, signature_tree, simple8b, transducer
from tolerant_gd.llm.tables import table, tokenizer_path


_WORDS = r"regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

OP4_SQL = f"""
WITH d AS (SELECT doc_id, row_number() OVER () AS r, coalesce({_WORDS}, []) AS w FROM documents),
b AS (SELECT item_id, w, least(10, len(w)) AS k FROM (SELECT item_id, coalesce({_WORDS}, []) AS w FROM benchmark) WHERE len(w) > 0),
bw AS (SELECT DISTINCT item_id, k, array_to_string(w[i : i + k - 1], ' ') AS g FROM (SELECT *, unnest(range(1, len(w) - k + 2)) AS i FROM b)),
dw AS (SELECT r, i, k, array_to_string(w[i : i + k - 1], ' ') AS g
       FROM (SELECT r, w, k, unnest(range(1, len(w) - k + 2)) AS i FROM d, (SELECT DISTINCT k FROM b) WHERE len(w) >= k)),
h AS (SELECT r, i, dw.k, item_id FROM dw JOIN bw ON dw.g = bw.g AND dw.k = bw.k),
p AS (SELECT r, count(DISTINCT q) AS n_hit FROM (SELECT r, unnest(range(i, i + k)) AS q FROM h) GROUP BY r),
t AS (SELECT r, count(DISTINCT item_id) AS n_items, string_agg(item, ',' ORDER BY item) AS items
      FROM (SELECT DISTINCT r, item_id, CAST(item_id AS VARCHAR) AS item FROM h) GROUP BY r)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN p USING (r) LEFT JOIN t USING (r)"""


def op1_simple8b(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simple8b.read_tokens(simple8b.write_tokens(table(spark, sf_dir, "documents"), tokenizer_path()))


def op2_mincut_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mincut_html.extract(table(spark, sf_dir, "pages"))


def op3_host_reputation(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    return host_reputation.judge(pages, host_reputation.label_outcomes(table(spark, sf_dir, "labels"), pages))


def op4_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op5_iso_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return iso_media.describe(iso_media.write_media(table(spark, sf_dir, "documents")))


def op6_rule_ensemble(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return rule_ensemble.score(docs, rule_ensemble.fit(docs, table(spark, sf_dir, "labels")))


def op7_bpe_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return transducer.encode_table(table(spark, sf_dir, "documents"), tokenizer_path())


def op8_signature_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return signature_tree.join(table(spark, sf_dir, "documents"))


def op9_ppm_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ppm_language.identify(table(spark, sf_dir, "documents"))


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.report(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_simple8b": op1_simple8b,
        "op2_mincut_html": op2_mincut_html,
        "op3_host_reputation": op3_host_reputation,
        "op4_decontaminate": op4_decontaminate,
        "op5_iso_media": op5_iso_media,
        "op6_rule_ensemble": op6_rule_ensemble,
        "op7_bpe_stream": op7_bpe_stream,
        "op8_signature_join": op8_signature_join,
        "op9_ppm_language": op9_ppm_language,
        "op10_secret_scan": op10_secret_scan,
    }


def oracle_sql() -> dict[str, str]:
    return {"op3_host_reputation": host_reputation.ORACLE, "op4_decontaminate": OP4_SQL}
