"""The operators as queries over whole tables: (spark, sf_dir) -> DataFrame."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, decontaminate, language_id, lm_scoring, near_dups, quality, sentence_pieces, sharding, substring_dedup, token_files
from .common import crc_bucket, documents


def tokenizer_file(name: str) -> bytes:
    """Bytes of a public tokenizer file of this machine, read on the driver and broadcast."""
    import public_tokenizers

    with open(public_tokenizers.path(name), "rb") as f:
        return f.read()


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = substring_dedup.remove_repeats(spark, documents(spark, sf_dir))
    return out.withColumnsRenamed({"__kept": "kept_spans", "__n_units": "n_units", "__n_removed": "n_removed"})


def op2_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.render_conversations(spark.read.parquet(f"{sf_dir}/conversations.parquet"))


def op3_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scoring.score_documents(spark, documents(spark, sf_dir, "doc_id", "text", "lang"))


def lm_base_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The columns of op3 that plain counts give."""
    out = lm_scoring.score_documents(spark, documents(spark, sf_dir, "doc_id", "text", "lang"))
    return out.select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", (F.round("base_score", 4) + F.lit(0.0)).alias("base_score"))


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.feistel_shards(documents(spark, sf_dir), shards=8)


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated_spans(spark, documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op6_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    manifest = token_files.encode_to_files(spark, documents(spark, sf_dir), tokenizer_file("byte_bpe_50k.json"))
    return token_files.read_files(manifest, int(spark.conf.get("spark.sql.shuffle.partitions"))).drop("file")


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_verdicts(documents(spark, sf_dir)).drop("rejected_by")


def op8_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dups.near_components(spark, documents(spark, sf_dir), words=3, percent=85).drop("__text_hash")


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir, "doc_id", "text", "lang")
    model = language_id.fit_language_model(docs.where(crc_bucket("doc_id", 4) != 2))
    return language_id.predict_languages(spark, docs, model)


def op10_sentence_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentence_pieces.sentence_piece_digests(spark, documents(spark, sf_dir), tokenizer_file("piece_bpe_32k.model"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_substring_dedup, op2_chat_formatting, op3_lm_scoring, lm_base_scores, op4_sharding, op5_decontamination, op6_token_output, op7_quality_rules, op8_near_duplicates, op9_language_id, op10_sentence_pieces)}


def oracle_sql() -> dict[str, str]:
    from . import oracles

    shards = oracles.sharding(sharding.round_keys(sharding.SEED), sharding._PRIME, 8)
    return {"op2_chat_formatting": chat.oracle(), "lm_base_scores": oracles.BASE_SCORES, "op4_sharding": shards, "op7_quality_rules": oracles.QUALITY, "op8_near_duplicates": oracles.NEAR_DUPLICATES}
