"""The corpus pipeline: language ID, near-duplicates, repeated passages, personal data, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from canopy.llm import langid, near_dups, packing, pii, repeats
from canopy.llm.common import crc_bucket, cut
from canopy.llm.entries import tokenizer_path


def identify(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text the language model accepts, with the columns they had."""
    model = langid.fit(docs.where(crc_bucket(F.col("doc_id"), 5) != 0))
    others = [c for c in docs.columns if c not in ("doc_id", "text")]
    held = docs.select("doc_id", "text", F.struct(*docs.columns).alias("canopy_row")) if others else docs.select("doc_id", "text", F.struct("doc_id", "text").alias("canopy_row"))
    slim = held.withColumn("canopy_row", F.col("canopy_row").dropFields("doc_id", "text")) if others else held
    got = langid.classify(slim if others else docs.select("doc_id", "text"), model, keep=["text", "canopy_row"] if others else ["text"]).where("accepted")
    return got.select(*(F.col(c) if c in ("doc_id", "text") else F.col("canopy_row").getField(c).alias(c) for c in docs.columns))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: five words, similarity 0.8."""
    return near_dups.drop_near_duplicates(docs, width=5, percent=80)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, without passages of 50 words that stand elsewhere too."""
    return repeats.strip(docs, repeats.WORDS, 50)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, personal data replaced."""
    return pii.sanitise(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all rows and the sequences that hold them."""
    return packing.pack(docs, tokenizer_path("byte_bpe_50k.json"))


STAGES = [("language_id", identify), ("near_duplicates", near_duplicates), ("repeated_passages", repeated_passages), ("personal_data", personal_data), ("packing", packed)]
#: Minhash signatures, word anchors and subword ids are not SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = cut(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
