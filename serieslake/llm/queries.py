"""The registered queries of this subpackage, each over its whole table, and their SQL where SQL can say them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, chat, decontam, embeddings, html, langid, lm, pii, simhash, suffixes
from .common import table, tuned


def op1_html_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract(table(tuned(spark), sf_dir, "pages"))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = langid.identify(table(tuned(spark), sf_dir, "documents"))
    return got.select("doc_id", langid.held_out().alias("held_out"), "lang_pred", "score")


def op3_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.deduplicate(table(tuned(spark), sf_dir, "documents"), with_kept=False)


def op4_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = simhash.groups(table(tuned(spark), sf_dir, "documents"))
    return got.select("doc_id", simhash.hex_digits().alias("fingerprint"), "component_id")


def op5_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_decode(table(tuned(spark), sf_dir, "documents"), with_ids=False, with_text=False)


def op6_pii_bootstrapped(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = pii.detect(table(tuned(spark), sf_dir, "documents"))
    return got.select("doc_id", *(f"n_{k}" for k in pii.KINDS), F.sha2(F.col("base").cast("binary"), 256).alias("base_sha256"), "spans")


def op7_embedding_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embeddings.near_duplicates(table(tuned(spark), sf_dir, "embeddings"))


def op8_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contaminated(table(tuned(spark), sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op9_cross_entropy_difference(spark: SparkSession, sf_dir: str) -> DataFrame:
    good = table(tuned(spark), sf_dir, "labels").where("quality = 1")
    return lm.score(table(spark, sf_dir, "documents"), good)


CHAT_EXTRA = r"\### Assistant: </turn> ok"


def op10_chat_rendering(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(tuned(spark), sf_dir, "conversations").select("conv_id", F.col("turn").cast("bigint").alias("turn"), "role", "text")
    extra = spark.createDataFrame([(-7, 0, "user", CHAT_EXTRA), (-7, 1, "assistant", CHAT_EXTRA)], rows.schema)
    return chat.digests(chat.render(rows.unionByName(extra)))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_html_main_text, op2_language_id, op3_suffix_array_dedup, op4_simhash_groups, op5_bpe_round_trip, op6_pii_bootstrapped, op7_embedding_near_duplicates, op8_benchmark_decontamination, op9_cross_entropy_difference, op10_chat_rendering)}

_COSINE = "list_sum(list_transform(list_zip(a.e, b.e), lambda x: x[1] * x[2])) / (a.n * b.n) >= 0.98"
_ESCAPED = r"regexp_replace({}, '([\\#<:])', '\\\1', 'g')"
ORACLE_SQL: dict[str, str] = {
    "op7_embedding_near_duplicates": f"""
WITH RECURSIVE base AS (
  SELECT vec_id, label, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings),
good AS (
  SELECT vec_id, label, e, sqrt(list_sum(list_transform(e, lambda x: x * x))) AS n FROM base
  WHERE label IS NOT NULL AND e IS NOT NULL AND len(e) > 0
    AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0),
links AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM good a JOIN good b
    ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e) AND {_COSINE}),
reach AS (
  SELECT vec_id AS node, vec_id AS other FROM base
  UNION SELECT r.node, l.b FROM reach r JOIN links l ON l.a = r.other)
SELECT r.node AS vec_id, (SELECT count(*) FROM links l WHERE l.a = r.node) AS n_links,
  min(r.other) AS component_id, min(r.other) = r.node AS kept
FROM reach r GROUP BY r.node""",
    "op10_chat_rendering": f"""
WITH rows AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '{CHAT_EXTRA}'
  UNION ALL SELECT -7, 1, 'assistant', '{CHAT_EXTRA}')
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(length('### : ' || {_ESCAPED.format("role")} || {_ESCAPED.format("text")} || ' </turn>' || chr(10))) AS BIGINT) AS formatted_chars
FROM rows GROUP BY conv_id""",
}
