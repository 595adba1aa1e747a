"""The queries of the training-data operators, each over its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coarsesample.llm import chat, decontaminate, html, language_id, near_text, near_vectors, packing, quality, sharding, token_files
from coarsesample.runtime import read_table, scratch_path, ship_package


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    docs, labels = read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels")
    kept_out = language_id.held_out(F.col("doc_id"))
    model = quality.train(docs, labels.where(~kept_out))
    return quality.score(docs, model).select("doc_id", kept_out.alias("held_out"), "score", "predicted")


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.assign_shards(read_table(spark, sf_dir, "documents"))
    return placed.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")


def op3_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = read_table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    said = "</s>[INST] ok [/INST]"
    own = spark.range(2).select(F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(said).alias("text"))
    return chat.read_back(chat.format_windows(given.unionByName(own)))


def op4_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return decontaminate.find_leaks(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))


def op5_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return html.extract(read_table(spark, sf_dir, "pages"))


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    docs = read_table(spark, sf_dir, "documents")
    kept_out = language_id.held_out(F.col("doc_id"))
    dictionaries = language_id.train_dictionaries(docs.where(~kept_out))
    found = language_id.predict_language(docs, dictionaries)
    return found.select("doc_id", kept_out.alias("held_out"), "lang_pred", "score", "rejected")


def op7_near_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return near_vectors.near_vectors(read_table(spark, sf_dir, "embeddings"))


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    pieces = packing.pack(read_table(spark, sf_dir, "documents"))
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset", "padded")


def op9_near_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return near_text.near_duplicates(read_table(spark, sf_dir, "documents"), width=3, num=85, den=100)


def op10_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    path = scratch_path(spark, "tokens")
    token_files.write_token_files(read_table(spark, sf_dir, "documents"), path)
    return token_files.read_token_files(spark, path)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_quality": op1_quality,
    "op2_sharding": op2_sharding,
    "op3_chat": op3_chat,
    "op4_leaks": op4_leaks,
    "op5_html": op5_html,
    "op6_language": op6_language,
    "op7_near_vectors": op7_near_vectors,
    "op8_packing": op8_packing,
    "op9_near_text": op9_near_text,
    "op10_token_files": op10_token_files,
}

#: Self joins over all pairs: what the two similarity operators have to find, by another way.
#: The others need learnt models, token ids, a parser, crc32 or windows of formatted text; tests hold them against brute force.
ORACLE_SQL: dict[str, str] = {
    "op7_near_vectors": """WITH RECURSIVE v AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
 link AS (SELECT a.vec_id AS u, b.vec_id AS w FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.e, b.e) >= 0.98),
 reach AS (SELECT vec_id AS u, vec_id AS w FROM v UNION SELECT r.u, l.w FROM reach r JOIN link l ON r.w = l.u),
 named AS (SELECT u, min(w) AS component_id FROM reach GROUP BY u), linked AS (SELECT u, count(*) AS n FROM link GROUP BY u)
 SELECT vec_id, coalesce(n, 0) AS n_links, component_id, vec_id = component_id AS kept FROM v JOIN named ON named.u = vec_id LEFT JOIN linked ON linked.u = vec_id""",
    "op9_near_text": r"""WITH RECURSIVE words AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS t FROM documents),
 sets AS (SELECT doc_id, CASE WHEN len(t) = 0 THEN CAST([] AS VARCHAR[]) WHEN len(t) < 3 THEN [array_to_string(t, ' ')] ELSE list_distinct(list_transform(range(1, len(t) - 1), lambda i: t[i] || ' ' || t[i + 1] || ' ' || t[i + 2])) END AS s FROM words),
 held AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM sets),
 met AS (SELECT a.doc_id AS u, b.doc_id AS w, any_value(a.n) AS nu, any_value(b.n) AS nw, count(*) AS n FROM held a JOIN held b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
 link AS (SELECT u, w FROM met WHERE 100 * n >= 85 * (nu + nw - n)), both_ways AS (SELECT u, w FROM link UNION ALL SELECT w, u FROM link),
 reach AS (SELECT doc_id AS u, doc_id AS w FROM sets UNION SELECT r.u, l.w FROM reach r JOIN both_ways l ON r.w = l.u),
 named AS (SELECT u, min(w) AS component_id FROM reach GROUP BY u)
 SELECT doc_id, CAST(len(s) AS BIGINT) AS n_shingles, component_id, doc_id = component_id AS kept FROM sets JOIN named ON named.u = doc_id""",
}
