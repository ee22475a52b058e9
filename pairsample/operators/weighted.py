"""Weighted baskets (t, i, w): the cosine of weight vectors by biased sampling.

With norms c(i) = sum of w^2 and u = w / sqrt(c), an occurrence of a pair is taken if u_i u_j mu / delta exceeds the draw; partners of an item are
again a prefix, in falling order of u. An occurrence taken with certainty counts u_i u_j mu / delta, any other 1, so the mean of the sum is
mu times similarity over delta. A pair is reported above mu/2, or, where every occurrence was certain and the sum so exact, from mu on.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.functions import draws
from pairsample.functions.measures import dbl


def normed(weighted: DataFrame) -> DataFrame:
    """(t, i, w, c, u)."""
    norms = weighted.groupBy("i").agg(F.sum(F.col("w") * F.col("w")).alias("c"))
    return weighted.join(norms, "i").select("t", "i", "w", "c", (F.col("w") / F.sqrt("c")).alias("u"))


def sample_weighted(weighted: DataFrame, mu: float, delta: float, seed: int = 42) -> DataFrame:
    """(i, j, s, k, certain): sum, occurrences taken, and whether all were certain; i < j by name."""
    rows = normed(weighted.where("w > 0")).withColumn("r", F.expr(draws.draw_sql(seed)))
    packed = rows.groupBy("t").agg(F.first("r").alias("r"), F.array_sort(F.collect_list(F.struct((-F.col("u")).alias("v"), "i"))).alias("a")).withColumn("n", F.size("a"))
    test = f"a[p - 1].v * a[mid - 1].v * {dbl(mu / delta)} > r"
    search = (
        "transform(sequence(1, n - 1), p -> aggregate(sequence(1, CAST(ceil(log2(n + 1)) AS INT)), named_struct('lo', p, 'hi', n), "
        "(s, x) -> IF(s.lo >= s.hi, s, element_at(transform(array((s.lo + s.hi + 1) DIV 2), "
        f"mid -> IF({test}, named_struct('lo', CAST(mid AS INT), 'hi', s.hi), named_struct('lo', s.lo, 'hi', CAST(mid - 1 AS INT)))), 1)), s -> named_struct('p', p, 'last', s.lo)))"
    )
    found = packed.where("n > 1").select("a", F.explode(F.expr(search)).alias("f")).where("f.last > f.p")
    pairs = found.select(F.expr("a[f.p - 1]").alias("x"), F.explode(F.expr("slice(a, f.p + 1, f.last - f.p)")).alias("y"))
    gain = F.expr(f"x.v * y.v * {dbl(mu / delta)}")
    each = pairs.select(F.least("x.i", "y.i").alias("i"), F.greatest("x.i", "y.i").alias("j"), F.greatest(F.lit(1.0), gain).alias("g"), (gain >= 1.0).alias("sure"))
    return each.groupBy("i", "j").agg(F.sum("g").alias("s"), F.count("*").alias("k"), F.every("sure").alias("certain"))


def report_weighted(sample: DataFrame, mu: float, delta: float) -> DataFrame:
    """(i, j, k, est_sim) of the pairs reported."""
    rows = sample.where(f"s > {dbl(mu / 2)} OR (certain AND s >= {dbl(mu * (1 - 1e-12))})")
    return rows.select("i", "j", "k", F.round(F.col("s") * delta / mu, 6).alias("est_sim"))


def exact_weighted(weighted: DataFrame, delta: float) -> DataFrame:
    """(i, j, sim) by the full product of weight vectors."""
    rows = normed(weighted.where("w > 0"))
    other = rows.select("t", F.col("i").alias("j"), F.col("u").alias("v"))
    sims = rows.join(other, "t").where("i < j").groupBy("i", "j").agg(F.sum(F.col("u") * F.col("v")).alias("sim"))
    return sims.where(F.col("sim") >= delta - 1e-12).select("i", "j", F.round("sim", 6).alias("sim"))
