"""Association rules of high confidence: all of them come from pairs with a high overlap coefficient."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.operators.baselines import exact_pairs
from pairsample.operators.refining import verify_exact
from pairsample.operators.reporting import report
from pairsample.operators.sampling import sample_pairs
from pairsample.operators.tiles import numbered, tile_sample


def rules_of(pairs: DataFrame, min_conf: float) -> DataFrame:
    """(lhs, rhs, k, confidence) in either direction."""
    both = F.explode(F.array(F.struct(F.col("i").alias("lhs"), F.col("j").alias("rhs"), F.col("ci").alias("c")), F.struct(F.col("j").alias("lhs"), F.col("i").alias("rhs"), F.col("cj").alias("c"))))
    rows = pairs.select("k", both.alias("x")).select("x.lhs", "x.rhs", "k", (F.col("k") / F.col("x.c")).alias("confidence"))
    return rows.where(F.col("confidence") >= min_conf - 1e-12).withColumn("confidence", F.round("confidence", 6))


def rules_exact(baskets: DataFrame, min_conf: float) -> DataFrame:
    return rules_of(exact_pairs(baskets, "overlap", min_conf), min_conf)


def rules_sampled(baskets: DataFrame, min_conf: float, mu: float = 15.0, seed: int = 42) -> DataFrame:
    """Rules of the pairs that sampling reports, with exact confidences: no false ones, and those missed as by the table of mu."""
    items = numbered(baskets)
    sample = sample_pairs(baskets, "overlap", mu, min_conf, seed) if items is None else tile_sample(baskets, items, "overlap", mu, min_conf, seed)
    found = report(sample, "overlap", mu, min_conf)
    return rules_of(verify_exact(found, baskets, "overlap", min_conf), min_conf)
