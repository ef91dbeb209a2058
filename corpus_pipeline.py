"""A corpus pipeline: each stage is a function of (spark, docs, sf_dir) that calls one operator.

All but the last return the columns of documents. Columns may hold nulls, texts may be empty or very
long, ids may repeat, and more columns may come along: they are left out.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from contrast.llm import bpe, mixing, quality, secret_scan, simhash
from contrast.llm.common import materialise, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: SQL lacks the hashes, the tokenizer and the tests; tests hold the stages against brute force.
ORACLE_SQL = None


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep, unchanged; what labels call good is the trusted text."""
    trusted = table(spark, sf_dir, "labels").where("quality = 1")
    judged = quality.judged(docs.select(*COLUMNS), trusted)
    # a filter would be moved down and the verdict computed twice; a generator stays in its place
    once = F.explode(F.when(F.col("kept"), F.array(F.lit(1))).otherwise(F.array().cast("array<int>")))
    return judged.select(*COLUMNS, once.alias("__one")).select(*COLUMNS)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates, on shingles of five words: the one with the least id.

    Near are fingerprints within four bits, and all pairs of a shingle similarity of 0.8 or more.

    Ids of null come after all others, equal ids go by a hash of the text. Of rows with equal id and
    text one stays.
    """
    key = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), F.xxhash64("text").alias("hash"))
    keyed = docs.select(*COLUMNS, key.alias("key"))
    found = simhash.near_duplicates(keyed, "key", width=5)
    stays = found.where(F.col("doc_id") == F.col("component_id")).select(F.col("doc_id").alias("key")).distinct()
    rest = [c for c in COLUMNS if c != "doc_id"]
    one = keyed.join(stays, "key", "left_semi").groupBy("key").agg(F.min_by(F.struct(*rest), F.struct("source", "lang", "n_chars")).alias("row"))
    return one.select(F.col("key.id").alias("doc_id"), *(F.col(f"row.{c}").alias(c) for c in rest)).select(*COLUMNS)


def secret_scans(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with a mark in place of each secret and n_chars to match.

    Null and empty texts, and texts without secrets, are unchanged; repeated rows are treated alike, and a
    text of any length and with any number of secrets is scanned whole.
    """
    text = secret_scan.redacted(F.col("text"), F.col("secrets"))
    found = secret_scan.scanned(docs.select(*COLUMNS))
    return found.withColumn("text", text).withColumn("n_chars", F.when(F.size("secrets") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(*COLUMNS)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """As many copies of each document as the mix takes of its words, rounded; none, and it goes.

    Rows with equal id, source and text each get the copies of the one of which most is taken.
    """
    keys = ["doc_id", "source", "text_hash"]
    plan = mixing.allot(docs).groupBy(*keys).agg(F.max(mixing.copies(F.col("size"), F.col("taken"))).alias("copies")).where("copies > 0")
    plan = plan.select(*(F.col(k).alias(f"__{k}") for k in keys), "copies")
    hashed = docs.select(*COLUMNS, F.xxhash64("text").alias("text_hash"))
    same = F.col("text_hash") == F.col("__text_hash")
    for k in keys[:2]:
        same &= F.col(k).eqNullSafe(F.col(f"__{k}"))
    return hashed.join(plan, same).select(*COLUMNS, F.explode(F.sequence(F.lit(1), "copies"))).select(*COLUMNS)


def byte_bpe(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, token_ids (little-endian unsigned 32-bit integers) and digests of the ids and of what they decode to.

    A null or empty text has no tokens and empty token_ids; repeated rows come out repeated, null ids stay null.
    A text of any length is encoded whole, one row at a time.
    """
    import public_tokenizers

    vocabulary, pattern = public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN
    both = bpe.round_trip(docs.select("doc_id", "text"), vocabulary, pattern)
    return both.select("doc_id", bpe.token_count(F.col("token_ids")).alias("n_tokens"), "token_ids", F.sha2("token_ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


STAGES = [("quality rules", quality_rules), ("near duplicates", near_dedup), ("secret scans", secret_scans), ("source mix", source_mix), ("byte BPE", byte_bpe)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents through all stages; each one's rows are written before the next reads them."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name.replace(" ", "_"))
    return STAGES[-1][1](spark, docs, sf_dir)
