"""Sources and sinks of baskets and results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def run_sql(spark: SparkSession, sf_dir: str, sql: str, **frames: DataFrame) -> DataFrame:
    """A query whose ``{name}`` marks stand for tables of the folder, or for the frames given."""
    used = {n: table(spark, sf_dir, n) for n in NAMES if "{" + n + "}" in sql and n not in frames}
    return spark.sql(sql, **used, **frames)


def read_basket_lines(spark: SparkSession, path: str, separator: str = r"\s+") -> DataFrame:
    """One basket per line of a text file, as (t, i): t is a hash of the file, the line and, for equal lines, their number among these.

    Line numbers don't exist in a distributed scan, so equal lines of a file get numbers by ``row_number``; any order among equal lines gives the same rows.
    """
    from pyspark.sql import Window

    lines = spark.read.text(path).select(F.col("_metadata.file_path").alias("file"), F.trim("value").alias("value")).where("value <> ''")
    numbered = lines.withColumn("n", F.row_number().over(Window.partitionBy("file", "value").orderBy("value")))
    return numbered.select(F.xxhash64("file", "value", "n").alias("t"), F.explode(F.array_distinct(F.split("value", separator))).alias("i"))


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None, mode: str = "errorifexists") -> None:
    writer = df.write.format(fmt).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def save_support(support: DataFrame, name: str, buckets: int = 64) -> None:
    """Supports as a table bucketed by item, so that later joins on the item don't shuffle it."""
    support.write.mode("overwrite").bucketBy(buckets, "i").sortBy("i").saveAsTable(name)


def stream_events(spark: SparkSession, path: str, schema=None) -> DataFrame:
    return spark.readStream.schema(schema or spark.read.parquet(path).schema).parquet(path)


def unpack(packed: DataFrame, column: str = "a") -> DataFrame:
    """Packed baskets as rows (t, c, i)."""
    return packed.select("t", F.inline(column))
