"""What the samples of many seeds report, without making their rows: draws are looked up at the occurrences of a pair where these are counted."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.functions.measures import Measure, get
from pairsample.operators import tiles
from pairsample.operators.baskets import enrich
from pairsample.operators.reporting import SURE
from pairsample.operators.sampling import last_admitted
from pairsample.operators.strips import DEALT, Found, over_strips, seed_draws
from pairsample.operators.tiles import similarity


def reports(of: Measure, mu: float, delta: float, m: float, k: np.ndarray, ci: np.ndarray, cj: np.ndarray) -> np.ndarray:
    """The printed rule over arrays."""
    return (k > mu / 2) | (k * of.array(ci, cj, delta, m) >= float(SURE))


def _sampled(f: Found, pairs: np.ndarray, chance: np.ndarray, seeds: range) -> Iterator[np.ndarray]:
    """For each seed how often each of the pairs is in the sample."""
    k = f.k[pairs]
    first = np.cumsum(k) - k
    of = f.of[np.repeat(f.begin[pairs] - first, k) + np.arange(k.sum())]
    chance = np.repeat(chance[pairs], k)
    for seed in seeds:
        yield np.add.reduceat(f.strip.draw(seed)[of] < chance, first, dtype=np.int64)


def missed_by_seed(baskets: DataFrame, items: pa.Table, measure: str | Measure, mu: float, delta: float, seeds: range, strips: int | None = None) -> DataFrame:
    """(seed, true_pairs, missed): the pairs at or above delta and those of them that the sample of the seed doesn't report."""
    of = get(measure)
    m = tiles._m(baskets, of)

    def made(f: Found) -> Iterator[pa.RecordBatch]:
        true = np.flatnonzero(similarity(of, f.k.astype(np.float64), f.ci, f.cj, m) >= delta - 1e-12)
        if len(true):
            chance = of.array(f.ci, f.cj, delta, m) * mu
            missed = [np.count_nonzero(~reports(of, mu, delta, m, k, f.ci[true], f.cj[true])) for k in _sampled(f, true, chance, seeds)]
            yield pa.RecordBatch.from_arrays([pa.array(seeds, pa.int64()), pa.array([len(true)] * len(seeds)), pa.array(missed)], names=["seed", "true_pairs", "missed"])

    parts = over_strips(baskets, items, made, "seed long, true_pairs long, missed long", seeds=seeds, chance=lambda ci, cj: of.array(ci, cj, delta, m) * mu, strips=strips)
    return parts.groupBy("seed").agg(F.sum("true_pairs").alias("true_pairs"), F.sum("missed").alias("missed"))


def reports_by_similarity(baskets: DataFrame, items: pa.Table, measure: str | Measure, mu: float, delta: float, seeds: range, steps: int = 10, strips: int | None = None) -> DataFrame:
    """(bucket, pairs, reports): co-occurring pairs by their similarity in ``steps`` of delta, and how often the samples of all seeds report them."""
    of = get(measure)
    m = tiles._m(baskets, of)

    def made(f: Found) -> Iterator[pa.RecordBatch]:
        bucket = np.floor(similarity(of, f.k.astype(np.float64), f.ci, f.cj, m) / delta * steps).astype(np.int64)
        times = np.zeros(len(f.k), np.int64)
        # a pair that all its occurrences wouldn't report can't be
        may = np.flatnonzero(reports(of, mu, delta, m, f.k, f.ci, f.cj))
        if len(may):
            for k in _sampled(f, may, of.array(f.ci, f.cj, delta, m) * mu, seeds):
                times[may] += reports(of, mu, delta, m, k, f.ci[may], f.cj[may])
        pairs, found = np.bincount(bucket), np.bincount(bucket, times).astype(np.int64)
        at = np.flatnonzero(pairs)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(pairs[at]), pa.array(found[at])], names=["bucket", "pairs", "reports"])

    parts = over_strips(baskets, items, made, "bucket int, pairs long, reports long", seeds=seeds, chance=lambda ci, cj: of.array(ci, cj, delta, m) * mu, strips=strips)
    return parts.groupBy("bucket").agg(F.sum("pairs").alias("pairs"), F.sum("reports").alias("reports"))


def inserted_by_seed(baskets: DataFrame, measure: str | Measure, mu: float, delta: float, seeds: range) -> DataFrame:
    """(seed, inserted): the occurrences of pairs in the sample of each seed that has any, counted from the supports of a transaction alone."""
    of = get(measure)
    m = tiles._m(baskets, of)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(seeds), np.int64)
        for batch in (part for whole in batches for part in tiles._slices(whole, DEALT)):
            sizes = pc.list_value_length(batch.column(0)).to_numpy(zero_copy_only=False).astype(np.int64)
            c = batch.column(0).flatten().to_numpy().astype(np.float64)
            begin = np.cumsum(sizes) - sizes
            most = of.array(c[begin], c[begin + 1], delta, m) * mu
            for n, value in enumerate(seed_draws([t.encode() for t in batch.column(1).to_pylist()], seeds)):
                r = value / 4294967296.0
                rows = np.flatnonzero(r < most)
                size = sizes[rows]
                first = np.cumsum(size) - size
                own = c[np.repeat(begin[rows] - first, size) + np.arange(size.sum())]
                total[n] += int((last_admitted(own, np.repeat(first + size - 1, size), np.repeat(r[rows], size), m, of, mu, delta) - np.arange(len(own))).sum())
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at + seeds[0]), pa.array(total[at])], names=["seed", "inserted"])

    packed = enrich(baskets).groupBy("t").agg(F.array_sort(F.collect_list("c")).alias("c")).where("size(c) > 1")
    return packed.select("c", F.col("t").cast("string").alias("t")).mapInArrow(run, "seed long, inserted long").groupBy("seed").agg(F.sum("inserted").alias("inserted"))
