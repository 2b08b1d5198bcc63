"""The registered queries of the training-data operators, each over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship_package
from . import chat, decontamination, html, language, mixing, privacy, sharding, similarity, telephony, toxicity


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship_package(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_html_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract_pages(table(spark, sf_dir, "pages"))


def op2_language_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return language.identify(docs, language.fit(docs))


def op3_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    own = spark.createDataFrame([(-7, 0, "user", "</s>[INST] ok [/INST]"), (-7, 1, "assistant", "</s>[INST] ok [/INST]")], "conv_id long, turn long, role string, text string")
    convs = table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", "text")
    return chat.chat_digests(convs.unionByName(own))


def op4_template_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op5_pareto_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_documents(table(spark, sf_dir, "documents"))


def op6_telephony_audio(spark: SparkSession, sf_dir: str) -> DataFrame:
    return telephony.media_digests(table(spark, sf_dir, "documents"))


def op7_toxicity_lexicon(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score_documents(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def op8_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similarity.similarity_components(table(spark, sf_dir, "documents"))


def op9_minimax_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(table(spark, sf_dir, "documents"))


def op10_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return privacy.find_personal_data(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_html_main_text, op2_language_crf, op3_chat_format, op4_template_decontamination, op5_pareto_mix, op6_telephony_audio, op7_toxicity_lexicon, op8_ngram_jaccard, op9_minimax_shards, op10_personal_data)}

# the mix in DuckDB's SQL: the same hash of the id, water level over sources and order within each
OP5_SQL = r"""
WITH d AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         (('0x' || substr(md5(doc_id::VARCHAR), 1, 13))::BIGINT::DOUBLE + 0.5) / 4503599627370496.0 AS u
  FROM documents),
s0 AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
s1 AS (SELECT *, ((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::BIGINT AS w FROM s0),
s2 AS (SELECT *, sum(source_size) OVER () AS total,
         3 * coalesce(sum(source_size) OVER (ORDER BY source_size / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before,
         sum(w) OVER (ORDER BY source_size / w, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS w_rest,
         row_number() OVER (ORDER BY source_size / w, source NULLS LAST) AS rn FROM s1),
s3 AS (SELECT *, (total - before) * w >= 3 * source_size * w_rest AS capped FROM s2),
o AS (SELECT total - before AS left_, w_rest AS w_open FROM s3 WHERE NOT capped ORDER BY rn LIMIT 1),
t AS (SELECT source, source_size, CASE WHEN capped THEN (3 * source_size)::DOUBLE ELSE (left_ * w)::DOUBLE / w_open::DOUBLE END AS target FROM s3 LEFT JOIN o ON true),
p AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size)::BIGINT ELSE 0 END AS whole FROM t),
q AS (SELECT *, target - whole * source_size AS need, CASE WHEN source_size > 0 THEN (target - whole * source_size) / source_size ELSE 0.0 END AS p FROM p),
r AS (SELECT d.doc_id, d.size, q.source_size, q.target, q.whole, q.need,
        sum(d.size) OVER (PARTITION BY d.source ORDER BY floor(d.u * 4096), CASE WHEN q.p > 0 THEN (d.u * (1 - q.p)) / ((1 - d.u) * q.p) END, d.doc_id ROWS UNBOUNDED PRECEDING) AS run
      FROM d JOIN q ON d.source IS NOT DISTINCT FROM q.source)
SELECT doc_id, size, source_size, target, (size * (whole + CASE WHEN need > 0 AND run - size / 2 <= need THEN 1 ELSE 0 END))::BIGINT AS taken,
       (whole + CASE WHEN need > 0 AND run - size / 2 <= need THEN 1 ELSE 0 END)::BIGINT AS copies
FROM r
"""

ORACLES = {"op5_pareto_mix": OP5_SQL}
