"""The registered queries of the training-data operators, with their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pairsample.llm import byte_bpe, decontamination, embedding_dedup, html_text, language_id, language_model, license_scan, line_dedup, order_minhash, token_counts


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold(of: int) -> Column:
    """crc32 of the id as text, modulo ``of``."""
    return F.crc32(F.col("doc_id").cast("string")) % of


def op1_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return order_minhash.near_duplicates(table(spark, sf_dir, "documents"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(table(spark, sf_dir, "documents"))


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    decoded = byte_bpe.round_trip(table(spark, sf_dir, "documents"))
    return decoded.select(
        "doc_id",
        (F.octet_length("ids") / 4).cast("long").alias("n_tokens"),
        F.sha2("ids", 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = line_dedup.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return kept.select("doc_id", "n_lines", "n_dropped", F.md5(F.encode("text", "UTF-8")).alias("text_md5"))


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = language_model.score_texts(table(spark, sf_dir, "documents"), fold(7) != 2, stable=True)
    return scored.select("doc_id", (fold(7) == 2).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents")
    model = language_id.train(documents.where(fold(4) != 2))
    found = language_id.identify(documents, model)
    return found.select("doc_id", (fold(4) == 2).alias("held_out"), "lang_pred", "score")


def op8_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dedup.linked_vectors(table(spark, sf_dir, "embeddings"))


def op9_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(license_scan.document_files(table(spark, sf_dir, "documents")))


def op10_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {
        "pipeline": pipeline,
        "op1_order_minhash": op1_order_minhash,
        "op2_token_counts": op2_token_counts,
        "op3_language_model": op3_language_model,
        "op4_line_dedup": op4_line_dedup,
        "op5_decontamination": op5_decontamination,
        "op6_byte_bpe": op6_byte_bpe,
        "op7_language_id": op7_language_id,
        "op8_embedding_dedup": op8_embedding_dedup,
        "op9_license_scan": op9_license_scan,
        "op10_html_text": op10_html_text,
    }


def oracle_sql() -> dict:
    return {
        "op4_line_dedup": line_dedup.ORACLE,
        "op5_decontamination": decontamination.ORACLE,
        "op9_license_scan": license_scan.oracle(),
    }
