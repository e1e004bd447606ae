"""One query per operator, with its production parameters, over its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from strata.llm import byte_bpe, chat, decontaminate, kd_shards, mixing, near_dup, pii, quality, secrets, token_counts
from strata.llm.common import read, sha_hex

TOKEN_LIMIT = 2048


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_chat_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = r"\### Assistant: </turn> ok"
    turns = read(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    extra = spark.range(2).select(F.lit(-7).cast("long"), F.col("id"), F.when(F.col("id") == 0, "user").otherwise("assistant"), F.lit(said))
    back = chat.read_back(chat.windows(turns.union(extra)))
    whole = back.groupBy("conv_id").agg(F.sum("n_turns").alias("n_turns"), F.sort_array(F.collect_list(F.struct("window", "turns", "loss"))).alias("w"), F.sum("chars").alias("formatted_chars"))
    turns_text, loss = F.array_join("w.turns", ""), F.array_join("w.loss", "")
    return whole.select("conv_id", "n_turns", sha_hex(turns_text).alias("turns_sha256"), F.length(loss).cast("long").alias("loss_chars"), sha_hex(loss).alias("loss_sha256"), "formatted_chars")


def of_kind(spans, kind: str):
    return F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.verdicts(read(spark, sf_dir, "documents"))


def op3_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    found = secrets.scan_secrets(docs, secrets.fit(docs))
    spans = F.col("spans")
    rules = secrets.digest(spans, secrets.KINDS[:3])
    return found.select("doc_id", *(of_kind(spans, k) for k in secrets.KINDS), sha_hex(rules).alias("base_sha256"), secrets.digest(spans, secrets.KINDS).alias("spans"))


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(read(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"), TOKEN_LIMIT)


def op5_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    ranks, pattern = vocabulary("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN
    encoded = byte_bpe.encode(read(spark, sf_dir, "documents"), ranks, pattern)
    digested = encoded.select("doc_id", "ids", F.size("ids").cast("long").alias("n_tokens"), sha_hex(F.array_join("ids", ",")).alias("ids_sha256"))
    decoded = byte_bpe.decode(digested, ranks, keep=("n_tokens", "ids_sha256"))
    return decoded.select("doc_id", "n_tokens", "ids_sha256", sha_hex(F.col("decoded")).alias("decoded_sha256"))


def op6_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(read(spark, sf_dir, "documents"), width=2, percent=80)


def op7_kd_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = kd_shards.shard(read(spark, sf_dir, "documents"), shards=8)
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), F.col("shard").cast("int"), "slot", F.lit(None).cast("int").alias("grown_shard"))


def op8_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    found = pii.find(docs, pii.fit(docs))
    return found.select("doc_id", *(of_kind(F.col("rules"), k) for k in pii.KINDS), F.size("added").cast("long").alias("n_added"), (F.size("rules") + F.size("added")).cast("long").alias("n_spans"), sha_hex(pii.digest(F.col("rules"))).alias("base_sha256"), pii.digest(F.concat("rules", "added")).alias("spans"))


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_items(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark"))


def op10_context_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.score_texts(read(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_chat_windows, op2_quality_rules, op3_secret_scan, op4_token_counts, op5_byte_bpe, op6_near_duplicates, op7_kd_shards, op8_pii, op9_decontamination, op10_context_mixing)}


def oracle_sql() -> dict[str, str]:
    return {"op2_quality_rules": quality.ORACLE_SQL}
