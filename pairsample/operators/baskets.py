"""The basket contract, supports, statistics and pruning."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def as_baskets(df: DataFrame, t: str, i: str, distinct: bool = False) -> DataFrame:
    """Rows (t, i) without nulls and repeats; ``distinct`` tells that the source has none, which saves a shuffle."""
    rows = df.select(F.col(t).alias("t"), F.col(i).alias("i")).where("t IS NOT NULL AND i IS NOT NULL")
    return rows if distinct else rows.distinct()


def support_counts(baskets: DataFrame, how: str = "hash", salts: int = 64) -> DataFrame:
    """(i, c), the number of transactions of each item; with ``sort`` (t, i, c), counted over sorted runs.

    Runs are salted by transaction, so a hot item's rows are spread over ``salts`` runs, both to be counted and to get their total.
    """
    if how == "hash":
        return baskets.groupBy("i").agg(F.count("*").alias("c"))
    salted = baskets.withColumn("salt", F.pmod(F.xxhash64("t"), F.lit(salts)).cast("int"))
    total = salted.groupBy("i", "salt").agg(F.count("*").alias("p")).groupBy("i").agg(F.sum("p").alias("c"), F.collect_list("salt").alias("salts"))
    # at most ``salts`` rows for each item: one for each of its runs
    spread = total.select("i", "c", F.explode("salts").alias("salt"))
    return salted.join(spread.hint("merge"), ["i", "salt"]).select("t", "i", "c")


def known_supports(baskets: DataFrame, broadcast_rows: int = 1_000_000) -> DataFrame | None:
    """The support table computed once and held as a local table, if it has at most ``broadcast_rows`` items; else None."""
    counts = support_counts(baskets)
    found = counts.limit(broadcast_rows + 1).toArrow()
    return baskets.sparkSession.createDataFrame(found, counts.schema) if found.num_rows <= broadcast_rows else None


def enrich(baskets: DataFrame, support: DataFrame | None = None, broadcast_rows: int = 1_000_000) -> DataFrame:
    """(t, i, c). The support table is broadcast only if a count shows that it has at most ``broadcast_rows`` items."""
    counts = support if support is not None else known_supports(baskets, broadcast_rows)
    if counts is None:
        return baskets.join(support_counts(baskets), "i").select("t", "i", "c")
    small = support is None or counts.limit(broadcast_rows + 1).count() <= broadcast_rows
    return baskets.join(F.broadcast(counts) if small else counts, "i").select("t", "i", "c")


def basket_stats(baskets: DataFrame) -> DataFrame:
    """One row: transactions m, items n, rows, mean and largest size, mean support."""
    sizes = baskets.groupBy("t").agg(F.count("*").alias("b"))
    by_size = sizes.agg(F.count("*").alias("m"), F.sum("b").alias("rows"), F.max("b").alias("max_b"))
    items = support_counts(baskets).agg(F.count("*").alias("n"))
    return by_size.crossJoin(items).select("m", "n", "rows", F.round(F.col("rows") / F.col("m"), 6).alias("b"), "max_b", F.round(F.col("rows") / F.col("n"), 6).alias("sigma"))


def prune(baskets: DataFrame, min_support: int, max_support: int | None = None) -> DataFrame:
    """Only items with a support in the given range."""
    kept = support_counts(baskets).where(F.col("c") >= min_support)
    kept = kept if max_support is None else kept.where(F.col("c") <= max_support)
    return baskets.join(kept.select("i"), "i", "left_semi").select("t", "i")


def transactions(baskets: DataFrame) -> DataFrame:
    """One row with m, to be joined where a measure needs it."""
    return baskets.agg(F.count_distinct("t").alias("m"))
