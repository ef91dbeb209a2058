"""The queries of this subpackage, by name, and the SQL twins of those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from contrast.llm import bpe, ctw, mixing, packing, quality, secret_scan, simhash, sketches, toxicity, warc
from contrast.llm.common import scratch_path, table


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return quality.judged(docs, table(spark, sf_dir, "labels").where("quality = 1")).drop("text")


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    warc.write_archives(table(spark, sf_dir, "pages"), path := scratch_path(spark, "archives"))
    return warc.read_archives(spark, path).drop("url")


def op3_iblt_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    blocks = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substr("text", F.lit(1), n - half), F.substr("next_text", F.lit(1), half))
    rows = sketches.neighbours(docs, blocks).select("doc_id", n.cast("long").alias("n_chars"), "text", edited.alias("edited"), "next_text")
    shown = rows.withColumn("edited_sha256", F.sha2(F.col("edited").cast("binary"), 256))
    return sketches.compared(shown).select("doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next")


def op4_ctw_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ctw.scored(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op5_best_fit_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return packing.shard_documents(docs, 40).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op6_weak_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.scored(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "labels")).drop("votes")


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return simhash.by_fingerprint(docs).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op8_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    vocabulary, pattern = public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return bpe.round_trip(docs, vocabulary, pattern).select("doc_id", bpe.token_count(F.col("token_ids")).alias("n_tokens"), F.sha2("token_ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op9_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    return mixing.allot(docs).select("doc_id", "size", "source_size", "target", "taken")


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    counts = [secret_scan.count_of(F.col("base"), kind).alias(f"n_{kind}") for kind in secret_scan.KINDS[:3]]
    digest = F.sha2(secret_scan.listed(F.col("base")).cast("binary"), 256).alias("base_sha256")
    return secret_scan.scanned(docs).select("doc_id", *counts, digest, secret_scan.listed(F.col("secrets")).alias("spans"))


QUERIES = {f.__name__: f for f in (op1_quality_rules, op2_warc, op3_iblt_fingerprints, op4_ctw_score, op5_best_fit_shards, op6_weak_toxicity, op7_simhash, op8_byte_bpe, op9_source_mix, op10_secret_scan)}
ORACLE_SQL: dict[str, str] = {"op2_warc": warc.ORACLE, "op9_source_mix": mixing.ORACLE}
