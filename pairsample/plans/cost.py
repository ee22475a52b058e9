"""Costs in hash operations (time) and hash entries (space), their expectations and the bounds on them."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.functions.errors import binomial_below_sql
from pairsample.functions.measures import Measure, dbl, get
from pairsample.operators.baselines import all_pairs
from pairsample.operators.baskets import support_counts, transactions
from pairsample.operators.reporting import rule_sql, with_transactions
from pairsample.operators.strips import MAX_ITEMS, strip_sums
from pairsample.operators.tiles import MAX_ITEMS as TILE_ITEMS
from pairsample.operators.tiles import numbered, tile_sums


def base(baskets: DataFrame) -> DataFrame:
    """One row: rows N, items n, and all pairs P of all transactions, from sizes alone."""
    sizes = baskets.groupBy("t").agg(F.count("*").alias("b"))
    by_size = sizes.agg(F.sum("b").alias("rows"), F.sum(F.expr("b * (b - 1) DIV 2")).alias("pairs"), F.count("*").alias("m"))
    return by_size.crossJoin(support_counts(baskets).agg(F.count("*").alias("n")))


def observed(baskets: DataFrame, sample: DataFrame) -> DataFrame:
    """time_s = N + insertions, space_s = n + distinct pairs of a drawn sample."""
    drawn = sample.agg(F.coalesce(F.sum("k"), F.lit(0)).alias("inserted"), F.count("*").alias("distinct_pairs"))
    return base(baskets).crossJoin(drawn).select((F.col("rows") + F.col("inserted")).alias("time_s"), (F.col("n") + F.col("distinct_pairs")).alias("space_s"))


def exact(baskets: DataFrame, pairs: DataFrame | None = None) -> DataFrame:
    """time_e = N + P, space_e = n + distinct co-occurring pairs."""
    distinct = (pairs if pairs is not None else all_pairs(baskets)).agg(F.count("*").alias("distinct_pairs"))
    return base(baskets).crossJoin(distinct).select((F.col("rows") + F.col("pairs")).alias("time_e"), (F.col("n") + F.col("distinct_pairs")).alias("space_e"))


def p_sql(measure: Measure, mu: float, delta: float) -> str:
    return f"least(1e0, {measure.weight_sql(delta)} * {dbl(mu)})"


def pair_sums(baskets: DataFrame, measure: str | Measure, mu: float, delta: float) -> DataFrame:
    """One row of sums over co-occurring pairs: expected insertions and entries, entries, pairs at or above delta, sum of similarities."""
    of = get(measure)
    if (items := numbered(baskets, MAX_ITEMS)) is not None:
        sums = (tile_sums if items.num_rows <= TILE_ITEMS else strip_sums)(baskets, items, of, mu, delta)
        zero = lambda c: F.coalesce(F.sum(c), F.lit(0).cast(sums.schema[c].dataType)).alias(c)
        return sums.agg(*[zero(c) for c in sums.columns])
    pairs = with_transactions(all_pairs(baskets), transactions(baskets) if of.uses_m else None)
    rows = pairs.withColumn("p", F.expr(p_sql(of, mu, delta))).withColumn("sim", F.expr(of.sim_sql()))
    return rows.agg(
        F.coalesce(F.sum(F.col("k") * F.col("p")), F.lit(0.0)).alias("inserted"), F.coalesce(F.sum(1 - F.pow(1 - F.col("p"), F.col("k"))), F.lit(0.0)).alias("entries"),
        F.count("*").alias("distinct_pairs"), F.count_if(F.col("sim") >= delta - 1e-12).alias("output"), F.coalesce(F.sum("sim"), F.lit(0.0)).alias("sum_sim"),
    )


def compare(baskets: DataFrame, measure: str | Measure = "cosine", mu: float = 15.0, delta: float = 0.5) -> DataFrame:
    """One row of the cost table: expected time and space of sampling, those of exact counting, their ratios, and the output."""
    both = base(baskets).crossJoin(pair_sums(baskets, measure, mu, delta))
    row = both.select(
        (F.col("rows") + F.col("inserted")).alias("ts"), (F.col("rows") + F.col("pairs")).cast("double").alias("te"), (F.col("n") + F.col("entries")).alias("ss"),
        (F.col("n") + F.col("distinct_pairs")).cast("double").alias("se"), "output",
    )
    return row.select(
        F.round("ts", 3).alias("time_s"), F.round("te", 3).alias("time_e"), F.round(F.col("te") / F.col("ts"), 6).alias("time_ratio"),
        F.round("ss", 3).alias("space_s"), F.round("se", 3).alias("space_e"), F.round(F.col("se") / F.col("ss"), 6).alias("space_ratio"), "output",
    )


def bounds(baskets: DataFrame, measure: str | Measure = "cosine", mu: float = 15.0, delta: float = 0.5, page: float = 1024.0, memory: float = 65536.0) -> DataFrame:
    """The analytic values of one workload, one row: see the names of the columns.

    ram: N log2 n + (mu/delta) sum of similarities. corollary: N log2 n + mu n^2, valid from the average similarity on. gain: the
    guaranteed factor over exact counting, b min(1/log2 b, sigma/(mu n)). independent: (n - 1) b, the sum of two-sided similarities of independent items.
    lower and output: N + z and N log2 n + mu z. io: page transfers of the shuffle form with pages of ``page`` and a memory of ``memory`` rows.
    """
    of = get(measure)
    sums = base(baskets).crossJoin(pair_sums(baskets, of, mu, delta))
    two = all_pairs(baskets).agg(F.sum(F.col("k") / F.col("ci") + F.col("k") / F.col("cj")).alias("two_sided"))
    rows = sums.crossJoin(two).withColumn("b", F.col("rows") / F.col("m")).withColumn("sigma", F.col("rows") / F.col("n")).withColumn("logn", F.log2(F.col("n").cast("double")))
    total = F.col("rows") + F.col("inserted")
    return rows.select(
        F.round(F.col("rows") * F.col("logn") + mu / delta * F.col("sum_sim"), 3).alias("ram"),
        F.round(F.col("rows") * F.col("logn") + mu * F.col("n") * F.col("n"), 3).alias("corollary"),
        F.round(2 * F.col("sum_sim") / (F.col("n") * (F.col("n") - 1)), 9).alias("average_similarity"),
        F.round(F.col("b") * F.least(1 / F.log2("b"), F.col("sigma") / (mu * F.col("n"))), 6).alias("gain"),
        F.when(F.col("sigma") < mu * F.col("n") / F.log2("b"), "pairs").otherwise("counting").alias("dominant"),
        F.round("two_sided", 3).alias("two_sided"), F.round((F.col("n") - 1) * F.col("b"), 3).alias("independent"),
        F.round(F.col("rows") + F.col("output"), 3).alias("lower"), F.round(F.col("rows") * F.col("logn") + mu * F.col("output"), 3).alias("output_bound"),
        F.round(total / page * F.greatest(F.lit(1.0), F.log(total / memory) / math.log(memory / page)), 3).alias("io"),
    )


def expected_output(baskets: DataFrame, measure: str | Measure, mu: float, delta: float, rule: str = "printed") -> DataFrame:
    """One row: expected reports among pairs at or above delta, and among the others, by the exact binomial tails."""
    of = get(measure)
    pairs = with_transactions(all_pairs(baskets), transactions(baskets) if of.uses_m else None).withColumn("p", F.expr(p_sql(of, mu, delta))).withColumn("sim", F.expr(of.sim_sql()))
    # below the cut the terms of the binomial are summed; the largest count not reported is the cut of mu/2, as below it no sampled pair is exact
    cut = int(mu // 2)
    sure = F.expr(f"CASE WHEN {rule_sql(of, mu, delta, rule)} THEN 1e0 ELSE 0e0 END")
    chance = F.when(F.col("p") >= 1, sure).otherwise(1 - F.expr(binomial_below_sql("k", "p", cut)))
    rows = pairs.withColumn("reported", chance).withColumn("true_pair", F.col("sim") >= delta - 1e-12)
    return rows.agg(F.round(F.sum(F.when(F.col("true_pair"), F.col("reported")).otherwise(0.0)), 3).alias("true_reports"), F.round(F.sum(F.when(F.col("true_pair"), 0.0).otherwise(F.col("reported"))), 3).alias("false_reports"))


def confusion(reported: DataFrame, true_pairs: DataFrame) -> DataFrame:
    """One row: true and false reports, misses, recall and precision."""
    a = reported.select("i", "j", F.lit(1).alias("r"))
    b = true_pairs.select("i", "j", F.lit(1).alias("t"))
    both = a.join(b, ["i", "j"], "full_outer")
    counts = both.agg(
        F.count_if(F.col("r").isNotNull() & F.col("t").isNotNull()).alias("tp"), F.count_if(F.col("t").isNull()).alias("fp"), F.count_if(F.col("r").isNull()).alias("fn")
    )
    # where nothing is true or nothing is reported the share is 0/0, no number, as in the check
    share = lambda of: F.round(F.coalesce(F.try_divide("tp", F.col("tp") + F.col(of)), F.lit(float("nan"))), 6)
    return counts.withColumn("recall", share("fn")).withColumn("precision", share("fp"))
