"""Queries of this subpackage: each applies one operator, with production parameters, to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rpqframe.llm import ann_forest, decontaminate, licenses, line_dedup, quote_links, secrets, simhash, sp_sampling, token_count, toxicity
from rpqframe.llm.common import read_table


def op1_ann_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann_forest.search(read_table(spark, sf_dir, "embeddings"), lambda i: i % 50 == 0, k=5)


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.dedup_report(read_table(spark, sf_dir, "documents"))


def op3_quote_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    threads = quote_links.reply_threads(read_table(spark, sf_dir, "conversations"))
    return threads.withColumn("own_sha256", F.sha2("own_text", 256)).drop("own_text")


def op4_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))


def op5_token_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_count.count_tokens(read_table(spark, sf_dir, "documents"))


def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = licenses.scan(read_table(spark, sf_dir, "documents"))
    return found.withColumn("n_detections", F.size("detections").cast("bigint")).drop("detections")


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    forest = secrets.train_forest(secrets.rule_findings(spark))
    found = secrets.scan(read_table(spark, sf_dir, "documents"), forest)
    best = F.aggregate("findings", F.lit(0.0), lambda a, f: F.greatest(a, f["p"]))
    places = F.array_join(F.transform("secrets", lambda f: F.concat_ws("-", f["s"], f["e"])), ",")
    return found.select("doc_id", F.size("findings").cast("bigint").alias("n_candidates"), F.size("secrets").cast("bigint").alias("n_secrets"), best.alias("score"), places.alias("places"))


def op8_sentencepiece_sampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sp_sampling.sample_report(read_table(spark, sf_dir, "documents"))


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(read_table(spark, sf_dir, "documents"))


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels")
    return toxicity.score(docs, toxicity.train_model(docs, labels))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    ops = (op1_ann_forest, op2_line_dedup, op3_quote_links, op4_decontaminate, op5_token_count, op6_license_scan, op7_secret_scan, op8_sentencepiece_sampling, op9_simhash, op10_toxicity)
    return {f.__name__: f for f in ops}


_WORDS = r"regexp_extract_all(translate({t}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

OP4_SQL = f"""
WITH items AS (
  SELECT CAST(item_id AS VARCHAR) AS item_id, {_WORDS.format(t="coalesce(text, '')")} AS w FROM benchmark WHERE item_id IS NOT NULL
), windows AS (
  SELECT DISTINCT item_id, least(13, len(w)) AS n, array_to_string(w[i:i + least(13, len(w)) - 1], ' ') AS g
  FROM items, unnest(range(1, len(w) - least(13, len(w)) + 2)) AS r(i) WHERE len(w) > 0
), docs AS (
  SELECT row_number() OVER () AS r, doc_id, {_WORDS.format(t="coalesce(text, '')")} AS w FROM documents
), places AS (
  SELECT r, i, n, array_to_string(w[i:i + n - 1], ' ') AS g
  FROM docs, (SELECT DISTINCT n FROM windows) AS sizes, unnest(range(1, len(w) - n + 2)) AS s(i) WHERE len(w) >= n
), hits AS (
  SELECT r, i, p.n, item_id FROM places AS p JOIN windows AS v ON p.g = v.g AND p.n = v.n
), words AS (
  SELECT r, count(DISTINCT k) AS n_hit FROM hits, unnest(range(i, i + n)) AS u(k) GROUP BY r
), found AS (
  SELECT r, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT item_id, ',' ORDER BY item_id) AS ids FROM hits GROUP BY r
)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM docs LEFT JOIN words USING (r) LEFT JOIN found USING (r)
"""


def oracle_sql() -> dict[str, str]:
    return {"op4_decontaminate": OP4_SQL}
