"""From sampled counts to reported pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.functions.measures import Measure, dbl, get

#: Slack of the test for exact pairs, so that a similarity of just delta passes in any engine.
SURE = "9.99999999999e-1"


def rule_sql(measure: Measure, mu: float, delta: float, rule: str = "printed", cut: float | None = None) -> str:
    """``printed``: k > mu/2 or k f >= 1. ``strict``: a pair taken with certainty by k f >= 1 alone, others by k > mu/2. ``all``: every sampled pair."""
    w = measure.weight_sql(delta)
    over = f"CAST(k AS DOUBLE) > {dbl(mu / 2 if cut is None else cut)}"
    sure = f"CAST(k AS DOUBLE) * {w} >= {SURE}"
    return {"printed": f"({over} OR {sure})", "strict": f"(CASE WHEN {w} * {dbl(mu)} >= 1e0 THEN {sure} ELSE {over} END)", "all": "(k >= 1)"}[rule]


def estimate_sql(measure: Measure, mu: float, delta: float) -> tuple[str, str, str]:
    """Whether the count is exact, the estimated co-occurrences and the estimated similarity."""
    p = f"least(1e0, {measure.weight_sql(delta)} * {dbl(mu)})"
    inter = f"(CAST(k AS DOUBLE) / {p})"
    return f"({measure.weight_sql(delta)} * {dbl(mu)} >= 1e0)", f"round({inter}, 6)", f"round({measure.sim(inter, 'CAST(ci AS DOUBLE)', 'CAST(cj AS DOUBLE)', 'CAST(m AS DOUBLE)')}, 6)"


def with_transactions(sample: DataFrame, m: DataFrame | None) -> DataFrame:
    return sample.crossJoin(F.broadcast(m)) if m is not None else sample.withColumn("m", F.lit(1).cast("long"))


def report(sample: DataFrame, measure: str | Measure, mu: float, delta: float, rule: str = "printed", cut: float | None = None, m: DataFrame | None = None) -> DataFrame:
    """(i, j, k, ci, cj, exact, est_inter, est_sim) of the pairs that the rule reports; ``m`` is the one-row table of transactions that lift needs."""
    of = get(measure)
    rows = with_transactions(sample, m if of.uses_m else None).where(rule_sql(of, mu, delta, rule, cut))
    exact, inter, sim = estimate_sql(of, mu, delta)
    return rows.select("i", "j", "k", "ci", "cj", F.expr(exact).alias("exact"), F.expr(inter).alias("est_inter"), F.expr(sim).alias("est_sim"))
