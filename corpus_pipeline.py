"""A corpus pipeline of five stages over the documents table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridcluster.llm import decontaminate, near_dups, quality, sentence_pieces, substring_dedup
from gridcluster.llm.queries import tokenizer_file
from gridcluster.session import materialise, ship


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base and all rules keep; null and empty texts fail the base, repeated rows share their verdict."""
    ship(spark)
    return quality.keep_good(docs)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies (five-word shingles, similarity 0.8) the document of least id stays; texts without a word stay all."""
    ship(spark)
    return near_dups.keep_one_of_each(spark, docs, words=5, percent=80)


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages and lines that an earlier document has are cut out; every document stays, with its new length (null for null text as before)."""
    ship(spark)
    out = substring_dedup.remove_repeats(spark, docs, report=False)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text").cast(docs.schema["n_chars"].dataType)))
    return out


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a passage of the benchmark; null and empty texts stay, and so do all if the benchmark is empty."""
    ship(spark)
    return decontaminate.drop_contaminated(spark, docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def sentence_piece_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Counts and digests of the ids of every document left; null and empty texts have the begin and the end id."""
    ship(spark)
    return sentence_pieces.sentence_piece_digests(spark, docs, tokenizer_file("piece_bpe_32k.model"))


STAGES = [
    ("quality_rules", quality_stage),
    ("near_duplicates", near_duplicate_stage),
    ("substring_dedup", substring_stage),
    ("benchmark_decontamination", decontamination_stage),
    ("sentence_pieces", sentence_piece_stage),
]

#: Tokenizing with a vocabulary file isn't expressible in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialise(spark, stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
