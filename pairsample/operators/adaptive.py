"""Sampling with a falling threshold: the most similar pairs first, without choosing delta beforehand.

An occurrence of a pair is in the sample for every delta below its own s*, at which the weight times mu is the draw. The sample at a
threshold is so the set of occurrences with s* above it, and a pair is reported from a level on that its sorted s* give: the
(floor(mu/2) + 1)-th of them, or the point at which its count so far would be exact.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pairsample.functions import draws
from pairsample.functions.measures import Measure, dbl, get
from pairsample.operators.baskets import transactions
from pairsample.operators.reporting import with_transactions
from pairsample.operators.sampling import ordered, pack, prefix_pairs, sample_rows
from pairsample.operators.strips import MAX_ITEMS, Found, named, over_strips
from pairsample.operators.tiles import _m, evaluate, numbered, similarity

INFINITE = "1e300"


def star_sql(measure: Measure, mu: float) -> str:
    """s* of an occurrence: very large where every threshold takes it (a draw of 0, or no solution)."""
    return f"coalesce(CASE WHEN r > 0e0 THEN {measure.solve_sql(f'(r / {dbl(mu)})')} END, {INFINITE})"


def occurrences(baskets: DataFrame, measure: str | Measure, mu: float, floor: float, seed: int = 42) -> DataFrame:
    """(i, j, ci, cj, s_star) of all occurrences that thresholds from ``floor`` up may take."""
    of = get(measure)
    rows = sample_rows(baskets, of, seed)
    pairs = prefix_pairs(pack(rows), of, mu, floor).join(rows.groupBy("t").agg(F.first("r").alias("r"), F.first("m").alias("m")), "t")
    return pairs.withColumn("s_star", F.expr(star_sql(of, mu))).where(F.col("s_star") > floor).select("i", "j", "ci", "cj", "s_star")


def levels(taken: DataFrame, measure: str | Measure, mu: float, m: DataFrame | None = None) -> DataFrame:
    """(i, j, ci, cj, level): the largest threshold at which the pair is reported by the printed rule."""
    of = get(measure)
    ranked = taken.withColumn("k", F.row_number().over(Window.partitionBy("i", "j").orderBy(F.col("s_star").desc())))
    ranked = with_transactions(ranked, m if of.uses_m else None)
    by_count = F.when(F.col("k") == int(mu // 2) + 1, F.col("s_star"))
    by_exact = F.least("s_star", F.expr(of.sim_sql()))
    return ranked.groupBy("i", "j").agg(F.first("ci").alias("ci"), F.first("cj").alias("cj"), F.greatest(F.max(by_count), F.max(by_exact)).alias("level"))


def strip_levels(baskets: DataFrame, items: pa.Table, measure: str | Measure, mu: float, floor: float, seed: int = 42, strips: int | None = None) -> DataFrame:
    """(i, j, ci, cj, level) of the pairs whose level is above ``floor``, found where the occurrences of a pair are."""
    of = get(measure)
    m = _m(baskets, of)
    kind = baskets.schema["i"].dataType.simpleString()
    names = baskets.sparkSession.sparkContext.broadcast(items["i"].combine_chunks())

    def made(f: Found) -> Iterator[pa.RecordBatch]:
        r = f.strip.fixed[0][f.of]
        pair = np.flatnonzero(np.repeat(of.array(f.ci, f.cj, floor, m) * mu, f.k) > r)
        r, pair = r[pair], np.repeat(np.arange(len(f.k)), f.k)[pair]
        star = np.full(len(r), float(INFINITE))
        some = r > 0
        star[some] = evaluate(of.solve("ci", "cj", "x", "m"), ci=f.ci[pair[some]], cj=f.cj[pair[some]], x=r[some] / mu, m=m)
        above = star > floor
        star, pair = star[above], pair[above]
        if not len(pair):
            return
        order = np.lexsort((-star, pair))
        star, pair = star[order], pair[order]
        begin = np.flatnonzero(np.append(True, pair[1:] != pair[:-1]))
        k = np.arange(len(pair)) - np.repeat(begin, np.diff(np.append(begin, len(pair)))) + 1
        level = np.minimum(star, similarity(of, k.astype(np.float64), f.ci[pair], f.cj[pair], m))
        level = np.maximum.reduceat(np.where(k == int(mu // 2) + 1, np.maximum(level, star), level), begin)
        at, level = pair[begin][level > floor], level[level > floor]
        yield from named(names, {"i": f.i[at], "j": f.j[at], "ci": f.ci[at].astype(np.int64), "cj": f.cj[at].astype(np.int64), "level": level})

    chance = lambda ci, cj: of.array(ci, cj, floor, m) * mu
    return over_strips(baskets, items, made, f"i {kind}, j {kind}, ci long, cj long, level double", (draws.draw_sql(seed),), chance=chance, strips=strips)


def enough_pairs(baskets: DataFrame, measure: str | Measure, mu: float = 15.0, min_results: int = 100, start: float = 1.0, ratio: float = 0.5, least: float = 1e-3, seed: int = 42) -> DataFrame:
    """(i, j, level) of every pair reported at the first threshold that reports at least ``min_results``. It falls by ``ratio`` from ``start``, to ``least`` at most.

    Only one number per step comes to the driver. Pairs of equal level stand or fall together, so the result doesn't depend on their names.
    """
    m = transactions(baskets) if get(measure).uses_m else None
    # only a solution without cases is evaluated over arrays
    items = numbered(baskets, MAX_ITEMS) if "CASE" not in get(measure).solve("ci", "cj", "x", "m") else None
    floor = start * ratio
    while True:
        if items is not None:
            found = strip_levels(baskets, items, measure, mu, floor, seed)
        else:
            found = levels(occurrences(baskets, measure, mu, floor, seed), measure, mu, m).where(F.col("level") > floor)
        if floor <= least or found.limit(min_results).count() >= min_results:
            return found.select("i", "j", "level")
        floor *= ratio


def top_pairs(baskets: DataFrame, measure: str | Measure, mu: float = 15.0, k: int = 100, start: float = 1.0, ratio: float = 0.5, least: float = 1e-3, seed: int = 42) -> DataFrame:
    """The k pairs of highest level, (i, j, level), ties by name, once the falling threshold reports as many."""
    found = enough_pairs(baskets, measure, mu, k, start, ratio, least, seed)
    return found.select("i", "j", F.round("level", 6).alias("level")).orderBy(F.col("level").desc(), "i", "j").limit(k)


def calibrate_delta(baskets: DataFrame, measure: str | Measure, mu: float = 15.0, target: int = 100, **options) -> DataFrame:
    """One row: the threshold at which about ``target`` pairs are reported."""
    return top_pairs(baskets, measure, mu, target, **options).agg(F.min("level").alias("delta"), F.count("*").alias("outputs"))


def frontier(baskets: DataFrame) -> DataFrame:
    """(t, i, j): for each item of a transaction the partner that a falling threshold takes first, the next one in order."""
    from pairsample.operators.baskets import enrich

    rows = ordered(enrich(baskets))
    after = Window.partitionBy("t").orderBy("place")
    return rows.withColumn("j", F.lead("i").over(after)).where("j IS NOT NULL").select("t", "i", "j")
