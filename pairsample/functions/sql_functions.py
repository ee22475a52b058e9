"""Measures as SQL functions of the session, inlined by the optimizer, and the pairs of one transaction as a table function."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from pairsample.functions.measures import MEASURES, get


def register_measures(spark: SparkSession) -> list[str]:
    """``sim_<measure>(k, ci, cj, m)`` and ``weight_<measure>(ci, cj, delta, m)`` as temporary functions."""
    made = []
    for name, of in MEASURES.items():
        args = "k DOUBLE, ci DOUBLE, cj DOUBLE, m DOUBLE"
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sim_{name}({args}) RETURNS DOUBLE RETURN {of.sim('k', 'ci', 'cj', 'm')}")
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION weight_{name}(ci DOUBLE, cj DOUBLE, delta DOUBLE, m DOUBLE) RETURNS DOUBLE RETURN {of.weight('ci', 'cj', 'delta', 'm')}")
        made += [f"sim_{name}", f"weight_{name}"]
    return made


def register_pairs_of(spark: SparkSession, measure: str = "cosine", name: str = "pairs_of") -> None:
    """``pairs_of(items, supports, r, delta, mu, m)``: the sampled pairs of one transaction, for lateral joins."""

    @F.udtf(returnType="i string, j string, ci bigint, cj bigint", useArrow=True)
    class PairsOf:
        def eval(self, items, supports, r: float, delta: float, mu: float, m: float):
            import numpy as np

            from pairsample.operators.sampling import last_admitted

            name, c = np.array([str(x) for x in items], object), np.array(supports, np.int64)
            if len(c) < 2:
                return
            order = np.lexsort((name, c))
            name, c = name[order], c[order]
            sizes = last_admitted(c, np.full(len(c), len(c) - 1), np.full(len(c), r), float(m), get(measure), mu, delta) - np.arange(len(c))
            x = np.repeat(np.arange(len(c)), sizes)
            y = x + 1 + np.arange(len(x)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
            yield from zip(name[x].tolist(), name[y].tolist(), c[x].tolist(), c[y].tolist(), strict=True)

    spark.udtf.register(name, PairsOf)
