"""The queries of these operators, thin over the operators, and their SQL where there is one."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spurline.llm import ann, bpe, chat, licenses, near_dup, packing, quality_fm, quality_rules, secret_scan, urls
from spurline.runtime import table


def op1_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return ann.nearest(rows, rows.where("vec_id % 100 = 0"), dim=64, k=10)


def op2_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pages that a policy rule fits are labelled URLs: rules are mined from them and judge the others."""
    return urls.judge_urls(table(spark, sf_dir, "pages").select("page_id", "url"))


def op3_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    odd = "</s>[INST] ok [/INST]"
    more = spark.range(1).select(F.explode(F.expr(f"array(struct(-7L as conv_id, 0L as turn, 'user' as role, '{odd}' as text), struct(-7L as conv_id, 1L as turn, 'assistant' as role, '{odd}' as text))")).alias("r")).select("r.*")
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(more)
    return chat.read_back(chat.format_conversations(rows))


def op4_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as P

    coded = bpe.code_documents(table(spark, sf_dir, "documents"), bpe.read_ranks(P.path("byte_bpe_multi_50k.tiktoken")), P.PATTERN)
    return coded.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op5_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan_documents(table(spark, sf_dir, "documents"))


def op6_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge_documents(table(spark, sf_dir, "documents")).drop("cleaned")


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = packing.pack_documents(table(spark, sf_dir, "documents"))
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "n_chars")
    model = quality_fm.train(docs, table(spark, sf_dir, "labels"))
    scored = quality_fm.score_documents(docs, model)
    return scored.select("doc_id", quality_fm.held_out().alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op9_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan_licenses(table(spark, sf_dir, "documents"))


def op10_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_dup.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


QUERIES = {f.__name__: f for f in (op1_nearest, op2_urls, op3_chat, op4_bpe, op5_secrets, op6_rules, op7_packing, op8_quality, op9_licenses, op10_near_dup)}
