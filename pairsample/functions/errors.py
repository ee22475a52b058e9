"""Error probabilities of reporting by sampled counts: a pair above the threshold is expected ``mu`` times or more, and reported above mu/2."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _cut(mu: float, cut: float | None) -> float:
    return mu / 2 if cut is None else cut


def fn_chernoff(mu: float) -> float:
    """Proven bound on the probability that a pair at or above the threshold is missed."""
    return math.exp(-mu / 8)


def fn_poisson(mu: float, cut: float | None = None) -> float:
    """P[X <= cut] for a Poisson variable of mean mu."""
    return sum(math.exp(-mu + k * math.log(mu) - math.lgamma(k + 1)) for k in range(math.floor(_cut(mu, cut)) + 1))


def fn_whole(mu: float) -> float:
    """Probability of a miss when every sampled pair is kept, so that only a count of 0 misses."""
    return math.exp(-mu)


def fp_poisson(ratio: float, mu: float, cut: float | None = None) -> float:
    """Probability that a pair of ``ratio`` times the threshold is reported."""
    mean = ratio * mu
    return 1 - sum(math.exp(-mean + k * math.log(mean) - math.lgamma(k + 1)) for k in range(math.floor(_cut(mu, cut)) + 1))


def fn_binomial(k: int, p: float, cut: float) -> float:
    """P[X <= cut] for k trials of probability p."""
    if p >= 1:
        return float(k <= cut)
    return sum(math.comb(k, x) * p**x * (1 - p) ** (k - x) for x in range(min(k, math.floor(cut)) + 1))


def mu_for(eps: float, kind: str = "chernoff") -> float:
    """The mu that holds misses to ``eps``: 8 ln(1/eps) by the proven bound, or the least whole number by the Poisson value."""
    if kind == "chernoff":
        return 8 * math.log(1 / eps)
    return next(mu for mu in range(1, 10_000) if fn_poisson(mu) <= eps)


def poisson_cdf(mean: str, upto: str) -> Column:
    """P[X <= upto], by a recurrence over the terms; ``mean`` and ``upto`` are SQL texts."""
    return F.expr(poisson_cdf_sql(mean, upto))


def poisson_cdf_sql(mean: str, upto: str) -> str:
    return f"aggregate(transform(sequence(0, CAST(floor({upto}) AS INT)), k -> exp(-({mean}) + k * ln({mean}) - aggregate(sequence(0, k), 0D, (a, x) -> a + ln(greatest(CAST(x AS DOUBLE), 1D))))), 0D, (a, x) -> a + x)"


def miss_table(spark: SparkSession, mus: list[float]) -> DataFrame:
    """mu against the three miss probabilities."""
    return misses(spark.createDataFrame([(float(mu),) for mu in mus], "mu double"))


def misses(rows: DataFrame) -> DataFrame:
    """The same for the column mu of a table."""
    return rows.select("mu", F.round(F.exp(-F.col("mu") / 8), 9).alias("proven"), F.round(poisson_cdf("mu", "mu / 2"), 9).alias("standard"), F.round(F.exp(-F.col("mu")), 15).alias("whole"))


def poisson_curves(spark: SparkSession, mu: float, ratios: list[float], upto: int = 40) -> DataFrame:
    """The probability of each count for pairs at some ratios of the threshold."""
    return count_chances(spark.createDataFrame([(float(r),) for r in ratios], "ratio double"), mu, upto)


def count_chances(ratios: DataFrame, mu: float, upto: int = 40) -> DataFrame:
    """The same for the column ratio of a table."""
    rows = ratios.select("ratio", F.explode(F.sequence(F.lit(0), F.lit(upto))).alias("k"))
    mean = F.col("ratio") * mu
    log_factorial = F.expr("aggregate(sequence(0, k), 0D, (a, x) -> a + ln(greatest(CAST(x AS DOUBLE), 1D)))")
    return rows.select(F.round("ratio", 6).alias("ratio"), "k", F.round(F.exp(-mean + F.col("k") * F.log(mean) - log_factorial), 9).alias("probability"))


def binomial_below_sql(k: str, p: str, cut: int) -> str:
    """The chance of at most ``cut`` successes in k trials of chance p, each term from the one before."""
    p = f"CAST({p} AS DOUBLE)"
    step = f"(a, x) -> named_struct('term', a.term * ({k} - x) / (x + 1e0) * {p} / (1e0 - {p}), 'sum', a.sum + a.term)"
    tail = f"aggregate(sequence(0, CAST(least({cut}, {k}) AS INT)), named_struct('term', pow(1e0 - {p}, CAST({k} AS DOUBLE)), 'sum', 0e0), {step}, a -> a.sum)"
    return f"CASE WHEN {p} < 1e0 THEN {tail} WHEN {k} <= {cut} THEN 1e0 ELSE 0e0 END"
