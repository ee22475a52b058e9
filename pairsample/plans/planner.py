"""Choice of a strategy, and an estimate of the sample before it is drawn."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.functions import draws
from pairsample.functions.measures import Measure, get
from pairsample.operators.baskets import basket_stats, support_counts
from pairsample.operators.sampling import arrow_counts, drawn, enrich, pack, with_m


def estimate(baskets: DataFrame, measure: str | Measure = "cosine", mu: float = 15.0, delta: float = 0.5, rate: float = 0.01, seed: int = 42) -> DataFrame:
    """One row: transactions looked at, insertions among them, and the insertions of the whole input.

    Whole transactions are drawn and sampled with the supports of all data, so the scaled number is unbiased.
    """
    of = get(measure)
    support = support_counts(baskets)
    thin = baskets.where(f"{draws.uniform_sql('t', seed + 1)} < {rate!r}D")
    rows = with_m(drawn(enrich(thin, support), seed), baskets, of)
    counted = arrow_counts(pack(rows), of, mu, delta).agg(F.coalesce(F.sum("k"), F.lit(0)).alias("inserted"))
    return thin.agg(F.count_distinct("t").alias("looked_at")).crossJoin(counted).withColumn("estimate", F.round(F.col("inserted") / rate, 3))


def choose_strategy(baskets: DataFrame, support: DataFrame | None, mu: float = 15.0, max_packed: int = 100_000) -> str:
    """The form that fits the input. No transaction has more items than there are, so a short support table settles it without a look at the transactions."""
    if support is not None and support.count() <= max_packed:
        return "arrow"
    return choose(baskets, mu, max_packed)["strategy"]


def choose(baskets: DataFrame, mu: float = 15.0, max_packed: int = 100_000, max_items: int = 50_000_000) -> dict:
    """The form that fits the input, from one row of statistics, and whether sampling can be expected to gain over exact counting."""
    s = basket_stats(baskets).first()
    if not s["n"]:
        return {"strategy": "arrow", "gains": False, "stats": s.asDict()}
    b = max(float(s["b"]), 2.0)
    strategy = "blocked" if s["max_b"] > max_packed else "shuffle" if s["n"] > max_items else "arrow"
    # with supports below this, pairs dominate and are mostly counted exactly anyway
    return {"strategy": strategy, "gains": float(s["sigma"]) >= mu * math.sqrt(s["n"]) / math.log2(b), "stats": s.asDict()}
