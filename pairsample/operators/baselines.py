"""What biased sampling is compared with: exact counting, pruned counting, item signatures, random hyperplanes, uniform sampling."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.functions import draws
from pairsample.functions.measures import Measure, get
from pairsample.operators.baskets import enrich, prune, transactions
from pairsample.operators.refining import minhash_sketch
from pairsample.operators.reporting import with_transactions
from pairsample.operators.sampling import count_pairs
from pairsample.operators.strips import MAX_ITEMS, strip_pairs
from pairsample.operators.tiles import MAX_ITEMS as TILE_ITEMS
from pairsample.operators.tiles import numbered, tile_pairs
from pairsample.operators.vectors import band_pairs


def all_pairs(baskets: DataFrame) -> DataFrame:
    """(i, j, k, ci, cj) of every co-occurring pair."""
    rows = enrich(baskets)
    left = rows.select("t", "i", F.col("c").alias("ci"))
    right = rows.select("t", F.col("i").alias("j"), F.col("c").alias("cj"))
    return count_pairs(left.join(right, "t").where("ci < cj OR (ci = cj AND i < j)"))


def exact_pairs(baskets: DataFrame, measure: str | Measure, delta: float) -> DataFrame:
    """(i, j, k, ci, cj, sim) of all pairs at or above delta."""
    of = get(measure)
    items = numbered(baskets, MAX_ITEMS)
    pairs = all_pairs(baskets) if items is None else (tile_pairs if items.num_rows <= TILE_ITEMS else strip_pairs)(baskets, items, of, delta)
    rows = with_transactions(pairs, transactions(baskets) if of.uses_m else None).withColumn("sim", F.expr(of.sim_sql()))
    return rows.where(F.col("sim") >= delta - 1e-12).select("i", "j", "k", "ci", "cj", F.round("sim", 6).alias("sim"))


def exact_pruned(baskets: DataFrame, measure: str | Measure, delta: float, min_support: int) -> DataFrame:
    return exact_pairs(prune(baskets, min_support), measure, delta)


def pruning_loss(baskets: DataFrame, measure: str | Measure, delta: float, min_support: int) -> DataFrame:
    """True pairs that support pruning loses."""
    return exact_pairs(baskets, measure, delta).join(exact_pruned(baskets, measure, delta, min_support).select("i", "j"), ["i", "j"], "left_anti")


def signature_all_pairs(baskets: DataFrame, size: int, at_least: float) -> DataFrame:
    """(i, j, est_jaccard): sketches of all items compared with each other. Quadratic in the items by its nature; the baseline whose cost is counted."""
    sketches = minhash_sketch(baskets, size).select("i", F.array(*[f"h{n}" for n in range(size)]).alias("x"))
    other = sketches.select(F.col("i").alias("j"), F.col("x").alias("y"))
    rows = sketches.join(other, F.col("i") < F.col("j")).withColumn("e", F.expr("size(filter(zip_with(x, y, (p, q) -> p = q), z -> z))") / F.lit(float(size)))
    return rows.where(F.col("e") >= at_least - 1e-12).select("i", "j", F.round("e", 6).alias("est_jaccard"))


def planes(bands: int, bits: int, dim: int, seed: int = 3):
    """(bands, bits, dim): the normals of random hyperplanes."""
    import numpy as np

    return np.random.default_rng(seed).standard_normal((bands, bits, dim)).round(6)


def hyperplane_pairs(vectors: DataFrame, id_col: str, vector_col: str, bits: int = 12, bands: int = 12, at_least: float = 0.9, seed: int = 3) -> DataFrame:
    """(i, j, cos): vectors that agree in all signs of one band of random hyperplanes, with their exact cosine."""
    first = vectors.select(F.size(vector_col).alias("n")).where("n > 0").first()
    dim = first["n"] if first else 1
    kind = "float" if vectors.schema[vector_col].dataType.simpleString() == "array<float>" else "double"
    rows = vectors.select(F.col(id_col).alias("v"), F.col(vector_col).cast(f"array<{kind}>").alias("x")).where((F.size("x") == dim) & F.col("v").isNotNull() & ~F.exists("x", F.isnull))
    return band_pairs(rows, planes(bands, bits, dim, seed), at_least).select("i", "j", F.round("cos", 6).alias("cos"))


def uniform_sample(baskets: DataFrame, rate: float, seed: int = 42) -> DataFrame:
    """(i, j, k, ci, cj) counted in a plain sample of the transactions, with the supports of all."""
    rows = enrich(baskets).where(f"{draws.uniform_sql('t', seed)} < {rate!r}D")
    left = rows.select("t", "i", F.col("c").alias("ci"))
    right = rows.select("t", F.col("i").alias("j"), F.col("c").alias("cj"))
    return count_pairs(left.join(right, "t").where("ci < cj OR (ci = cj AND i < j)"))
