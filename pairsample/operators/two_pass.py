"""Sampling in two passes with a counting filter: only pairs whose filter count could be reported are counted exactly.

A filter never counts too few, so what is reported is the same as without it.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.functions.measures import Measure, dbl, get
from pairsample.operators.reporting import SURE
from pairsample.operators.sampling import count_pairs, pack, prefix_pairs, sample_rows


def slots(width: int, depth: int) -> list:
    """One slot per row of the filter for the pair (i, j)."""
    return [(F.pmod(F.xxhash64(F.lit(d), F.col("i").cast("string"), F.col("j").cast("string")), F.lit(width)) + d * width).alias(f"s{d}") for d in range(depth)]


def sample_two_pass(baskets: DataFrame, measure: str | Measure, mu: float, delta: float, seed: int = 42, width: int = 1 << 16, depth: int = 2) -> DataFrame:
    """(i, j, k, ci, cj) of the sampled pairs that pass the filter; a superset of those reported."""
    of = get(measure)
    pairs = prefix_pairs(pack(sample_rows(baskets, of, seed)), of, mu, delta)
    return gate(pairs, of, mu, delta, width, depth)


def gate(pairs: DataFrame, of: Measure, mu: float, delta: float, width: int, depth: int) -> DataFrame:
    """Pass one fills the filter; pass two makes the pairs again and counts those that may reach mu/2 or be exact."""
    marked = pairs.select("i", "j", "ci", "cj", "m" if "m" in pairs.columns else F.lit(1).alias("m"), *slots(width, depth))
    # the filter is a table of at most width * depth counters
    counters = marked.select(F.explode(F.array(*[f"s{d}" for d in range(depth)])).alias("slot")).groupBy("slot").agg(F.count("*").alias("cnt"))
    # counters of a wide filter are shuffled
    sent = F.broadcast if width * depth <= 1 << 20 else lambda df: df
    probed = marked
    for d in range(depth):
        probed = probed.join(sent(counters.select(F.col("slot").alias(f"s{d}"), F.col("cnt").alias(f"n{d}"))), f"s{d}")
    most = F.least(*[f"n{d}" for d in range(depth)]) if depth > 1 else F.col("n0")
    kept = probed.withColumn("most", most.cast("double")).where(f"most > {dbl(mu / 2)} OR most * {of.weight_sql(delta)} >= {SURE}")
    return count_pairs(kept.select("i", "j", "ci", "cj"))


def exact_two_pass(baskets: DataFrame, measure: str | Measure, delta: float, width: int = 1 << 16, depth: int = 2) -> DataFrame:
    """Exact counting behind a counting filter: (i, j, k, ci, cj, sim) at or above delta."""
    of = get(measure)
    rows = sample_rows(baskets, of)
    left = rows.select("t", "m", "i", F.col("c").alias("ci"))
    right = rows.select("t", F.col("i").alias("j"), F.col("c").alias("cj"))
    pairs = left.join(right, "t").where("ci < cj OR (ci = cj AND i < j)")
    # no count passes mu/2 here: a pair stays only if the filter lets it be exact
    kept = gate(pairs, of, 1e18, delta, width, depth)
    scored = kept.withColumn("m", F.lit(1)).withColumn("sim", F.expr(of.sim_sql()))
    return scored.where(F.col("sim") >= delta - 1e-12).select("i", "j", "k", "ci", "cj", F.round("sim", 6).alias("sim"))


def cms_counts(pairs: DataFrame, eps: float = 0.001, confidence: float = 0.99, seed: int = 1) -> DataFrame:
    """The engine's count-min sketch over pairs, one binary row: the alternative to the table of counters."""
    return pairs.agg(F.count_min_sketch(F.xxhash64("i", "j"), F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sketch"))


class CountMin:
    """The engine's serialised sketch, read back: counts that are never too small."""

    def __init__(self, raw: bytes) -> None:
        _, _, depth, width = struct.unpack_from(">iqii", raw)
        self.factors = np.frombuffer(raw, ">i8", depth, 20).astype(np.int64)
        self.counts = np.frombuffer(raw, ">i8", depth * width, 20 + 8 * depth).astype(np.int64).reshape(depth, width)

    def at(self, items: np.ndarray) -> np.ndarray:
        least = np.full(len(items), np.iinfo(np.int64).max)
        with np.errstate(over="ignore"):
            for factor, row in zip(self.factors, self.counts, strict=True):
                place = items * factor
                place = (place + (place >> 32)) & ((1 << 31) - 1)
                least = np.minimum(least, row[place % len(row)])
        return least


def with_estimates(pairs: DataFrame, sketch: DataFrame) -> DataFrame:
    """Adds ``most``, the sketch's count of each pair (i, j, ci, cj). The sketch is one row, of a size that eps and confidence set."""
    known = CountMin(bytes(sketch.first()["sketch"]))
    sent = pairs.sparkSession.sparkContext.broadcast(known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], pa.array(sent.value.at(batch.column(4).to_numpy()))], names=["i", "j", "ci", "cj", "most"])

    kind = pairs.schema["i"].dataType.simpleString()
    return pairs.select("i", "j", "ci", "cj", F.xxhash64("i", "j").alias("h")).mapInArrow(run, f"i {kind}, j {kind}, ci long, cj long, most long")


def sample_count_min(baskets: DataFrame, measure: str | Measure, mu: float, delta: float, seed: int = 42, eps: float = 1e-4, confidence: float = 0.99) -> DataFrame:
    """(i, j, k, ci, cj) of the sampled pairs that the sketch lets reach mu/2 or be exact; a superset of those reported."""
    of = get(measure)
    pairs = prefix_pairs(pack(sample_rows(baskets, of, seed)), of, mu, delta)
    probed = with_estimates(pairs, cms_counts(pairs, eps, confidence)).withColumn("m", F.lit(1).cast("long"))
    kept = probed.where(f"most > {dbl(mu / 2)} OR most * {of.weight_sql(delta)} >= {SURE}")
    return count_pairs(kept.select("i", "j", "ci", "cj"))


def count_min_bounds(pairs: DataFrame, eps: float = 1e-4, confidence: float = 0.99) -> DataFrame:
    """One row: pairs, those that the sketch counts too low (none can be), and whether nearly all stay within its promise of eps times the insertions."""
    found = with_estimates(count_pairs(pairs), cms_counts(pairs, eps, confidence)).join(count_pairs(pairs).select("i", "j", "k"), ["i", "j"])
    total = pairs.agg(F.count("*").alias("n"))
    rows = found.crossJoin(F.broadcast(total)).agg(F.count("*").alias("pairs"), F.count_if(F.col("most") < F.col("k")).alias("too_few"), F.count_if(F.col("most") > F.col("k") + eps * F.col("n")).alias("far"))
    return rows.select("pairs", "too_few", (F.col("far") <= F.col("pairs") * (1 - confidence)).alias("close"))
