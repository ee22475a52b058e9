"""A corpus cleaned and encoded in five stages, each reading the table that the one before has written.

Language identification drops texts without a known language; line deduplication drops lines that an earlier document holds and documents
of which nothing is left; near-duplicate search leaves one document of each group; decontamination drops documents that hold a benchmark item;
the rest is encoded to tokens and decoded again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairsample.llm import byte_bpe, decontamination, language_id, line_dedup, order_minhash
from pairsample.llm.common import Scratch


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language_id.keep_identified(docs, language_id.train(docs))


def deduplicate_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    found = line_dedup.dedup_lines(docs)
    emptied = (F.col("n_dropped") > 0) & (F.btrim("text", F.lit(line_dedup.BLANKS + "\n")) == "")
    return found.where(~emptied).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    others = order_minhash.near_duplicates(docs).where(~F.col("kept")).select("doc_id")
    return docs.join(others, "doc_id", "left_anti").select(*docs.columns)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontamination.remove_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select(*docs.columns)


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    decoded = byte_bpe.round_trip(docs)
    return decoded.select(
        "doc_id",
        (F.octet_length("ids") / 4).cast("long").alias("n_tokens"),
        F.sha2("ids", 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )


STAGES = [
    ("language identification", identify_language),
    ("line deduplication", deduplicate_lines),
    ("near duplicates", drop_near_duplicates),
    ("benchmark decontamination", decontaminate),
    ("byte-level BPE", encode_tokens),
]
#: SQL can't express the learned language model or the encoding; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages, from ``documents`` to one row per document kept."""
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES:
        docs = scratch.write(stage(spark, docs, sf_dir))
    return docs
