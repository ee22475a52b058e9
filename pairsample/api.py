"""The calls a user needs: find associated pairs, find rules, compare costs."""

from __future__ import annotations

from pyspark.sql import DataFrame

from pairsample.functions.measures import Measure, get
from pairsample.operators.baskets import known_supports, support_counts, transactions
from pairsample.operators.refining import filter_minhash, filter_smaller_set, minhash_sketch, verify_exact
from pairsample.operators.reporting import report
from pairsample.operators.rules import rules_exact, rules_sampled
from pairsample.operators.sampling import sample_pairs
from pairsample.plans.cost import compare
from pairsample.plans.planner import choose_strategy

__all__ = ["compare", "find_pairs", "rules_exact", "rules_sampled"]


def find_pairs(
    baskets: DataFrame, measure: str | Measure = "cosine", delta: float = 0.5, mu: float = 15.0, seed: int = 42,
    rule: str = "printed", refine: str = "exact", strategy: str | None = None, sketch_size: int = 64, rate: float = 0.1,
    held_rows: int = 4_000_000,
) -> DataFrame:
    """Pairs of items whose similarity reaches ``delta``, from distinct rows (t, i).

    A true pair is missed with a small probability set by ``mu`` (1.8 % at 15). ``refine`` removes false reports: ``exact`` by counting the
    reported pairs, ``minhash`` by sketches, ``smaller`` by probing the smaller set, ``none`` not at all.
    """
    of = get(measure)
    # baskets of few rows are read once and held; the limit is what proves that they are few
    held = baskets.select("t", "i").limit(held_rows + 1).toArrow()
    if held.num_rows <= held_rows:
        spark, counts = baskets.sparkSession, held.group_by("i").aggregate([("t", "count")]).rename_columns(["i", "c"])
        support = spark.createDataFrame(counts, support_counts(baskets).schema)
        baskets = spark.createDataFrame(held, baskets.select("t", "i").schema)
    else:
        held, support = None, known_supports(baskets)
    m = transactions(baskets) if of.uses_m else None
    how = strategy or choose_strategy(baskets, support, mu)
    found = report(sample_pairs(baskets, of, mu, delta, seed, how, support=support), of, mu, delta, rule, m=m)
    if refine == "exact":
        return verify_exact(found, baskets, of, delta, m, sets=held)
    if refine == "minhash":
        return filter_minhash(found, minhash_sketch(baskets, sketch_size), sketch_size, of, delta, m)
    if refine == "smaller":
        return filter_smaller_set(found, baskets, rate, of, delta, m)
    return found
