"""Second phases that remove false reports: exact counting, min-wise sketches, and probing the smaller set."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.functions import draws
from pairsample.functions.measures import Measure, get
from pairsample.operators.baskets import transactions
from pairsample.operators.held import checkpointed, release
from pairsample.operators.reporting import with_transactions
from pairsample.operators.strips import MAX_ITEMS, Found, named, over_strips
from pairsample.operators.tiles import _m, numbered, over_tiles, similarity, tile_pairs

#: A prime below 2^31, so that products of two numbers below it stay inside 63 bits.
PRIME = 2147483647
#: Rows looked up at once, and pairs sent to all tasks at most.
LOOK_UPS, SENT = 4_000_000, 500_000


def counted_in_memory(candidates: DataFrame, sets: pa.Table) -> DataFrame:
    """(i, j, k, ci, cj) of candidates (i, j, ci, cj, sure, k), each that isn't sure counted where it stands against broadcast sets (i, t): the rows of j are marked, those of i looked up."""
    codes = sets["i"].combine_chunks().dictionary_encode()
    item = codes.indices.to_numpy(zero_copy_only=False)
    place = np.argsort(item, kind="stable")
    at = sets["t"].combine_chunks().dictionary_encode().indices.to_numpy(zero_copy_only=False).astype(np.int32)[place]
    ends = np.cumsum(np.bincount(item, minlength=len(codes.dictionary)))
    sent = candidates.sparkSession.sparkContext.broadcast((codes.dictionary, at, ends))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items, at, ends = sent.value
        begins = np.append(0, ends[:-1])
        marked = np.zeros(int(at.max()) + 1 if len(at) else 1, bool)
        for batch in batches:
            i, j = (pc.index_in(batch.column(x), value_set=items).to_numpy(zero_copy_only=False) for x in (0, 1))
            sure, k = (batch.column(x).to_numpy(zero_copy_only=False) for x in (4, 5))
            k = k.copy()
            order = np.flatnonzero(~sure)
            order = order[np.argsort(j[order], kind="stable")]
            for rows in np.split(order, np.flatnonzero(np.diff(j[order])) + 1) if len(order) else ():
                own = at[begins[j[rows[0]]] : ends[j[rows[0]]]]
                marked[own] = True
                sizes = ends[i[rows]] - begins[i[rows]]
                starts = np.cumsum(sizes) - sizes
                for part in np.split(np.arange(len(rows)), np.flatnonzero(np.diff(starts // LOOK_UPS)) + 1):
                    size = sizes[part]
                    first = np.cumsum(size) - size
                    seen = marked[at[np.repeat(begins[i[rows[part]]] - first, size) + np.arange(size.sum())]]
                    k[rows[part]] = np.add.reduceat(seen, first, dtype=np.int64)
                marked[own] = False
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], pa.array(k), *batch.columns[2:4]], names=["i", "j", "k", "ci", "cj"])

    kind = candidates.schema["i"].dataType.simpleString()
    return candidates.select("i", "j", "ci", "cj", "sure", "k").mapInArrow(run, f"i {kind}, j {kind}, k long, ci long, cj long")


def verify_exact(pairs: DataFrame, baskets: DataFrame, measure: str | Measure, delta: float, m: DataFrame | None = None, in_memory_rows: int = 4_000_000, sets: pa.Table | None = None) -> DataFrame:
    """(i, j, k, ci, cj, sim) of the candidate pairs whose exact similarity reaches delta.

    Pairs that the report marks as exact keep their count. The others are counted against sets held in memory where the baskets have at most
    ``in_memory_rows`` rows, which is checked (``sets`` if they are there already); beyond that by tiles, or where there are too many items for these,
    candidates meet the rows of i, then those of (j, t).
    """
    of = get(measure)
    counted = F.col("exact") if "exact" in pairs.columns else F.lit(False)
    candidates = pairs.select("i", "j", "ci", "cj", counted.alias("sure"), F.col("k") if "k" in pairs.columns else F.lit(0).cast("long").alias("k"))
    items = None
    if sets is None:
        # the supports tell how many rows there are
        items = numbered(baskets)
        if items is None or (pc.sum(items["c"]).as_py() or 0) <= in_memory_rows:
            sets = baskets.select("i", "t").limit(in_memory_rows + 1).toArrow()
    if sets is not None and sets.num_rows <= in_memory_rows:
        both = counted_in_memory(candidates, sets)
    else:
        if items is not None and (not of.uses_m or m is not None):
            # all pairs are counted where they stand, and of those that reach delta the candidates are kept
            return _among(lambda: _reaching(tile_pairs(baskets, items, of, delta), of, delta, m), candidates.select("i", "j"))
        at = candidates.where("NOT sure").join(baskets, "i").select("t", "i", "j", "ci", "cj")
        met = at.join(baskets.select(F.col("t"), F.col("i").alias("j")), ["t", "j"])
        both = met.groupBy("i", "j").agg(F.count("*").alias("k"), F.first("ci").alias("ci"), F.first("cj").alias("cj"))
        both = both.unionByName(candidates.where("sure").select("i", "j", "k", "ci", "cj"))
    return _reaching(both, of, delta, m)


def _among(true: Callable[[], DataFrame], candidates: DataFrame) -> DataFrame:
    """The true pairs that are candidates. Candidates are many: they are only shuffled if the true pairs, which are counted first, are many too."""
    # no name is kept for the plan, as it would keep its shuffle files
    found = checkpointed(true())
    if found is None:
        return true().join(candidates, ["i", "j"], "left_semi")
    release(found.sparkSession)
    if found.count() > SENT:
        return found.join(candidates, ["i", "j"], "left_semi")
    return candidates.join(F.broadcast(found), ["i", "j"]).select(*found.columns).distinct()


def _reaching(both: DataFrame, of: Measure, delta: float, m: DataFrame | None) -> DataFrame:
    rows = with_transactions(both, m if of.uses_m else None).withColumn("sim", F.expr(of.sim_sql()))
    return rows.where(F.col("sim") >= delta - 1e-12).select("i", "j", "k", "ci", "cj", F.round("sim", 6).alias("sim"))


def hash_family(size: int, seed: int = 1) -> list[tuple[int, int]]:
    """Factors and offsets of ``size`` almost min-wise hash functions (a x + b) mod p."""
    out, x = [], seed * 7919 + 12345
    for _ in range(size):
        x = (x * 48271) % PRIME
        a = x
        x = (x * 48271) % PRIME
        out.append((a, x))
    return out


def base_sql(text: str, dialect: str = draws.SPARK) -> str:
    """A whole number below the prime for each transaction, from its MD5."""
    return f"CAST(floor({draws.uniform_sql(text, 0, dialect)} * 2147483647e0) AS BIGINT)"


def minhash_sketch(baskets: DataFrame, size: int, seed: int = 1) -> DataFrame:
    """(i, h0, h1, ...): the least value of each hash function over the item's transactions, by plain minima."""
    x = baskets.select("i", F.expr(base_sql("t")).alias("x"))
    return x.groupBy("i").agg(*[F.min((F.col("x") * a + b) % PRIME).alias(f"h{n}") for n, (a, b) in enumerate(hash_family(size, seed))])


def filter_minhash(pairs: DataFrame, sketches: DataFrame, size: int, measure: str | Measure, delta: float, m: DataFrame | None = None) -> DataFrame:
    """(i, j, est_jaccard, est_sim) of the pairs whose similarity, by the share of equal sketch values, reaches delta."""
    of = get(measure)
    left = sketches.select("i", F.array(*[f"h{n}" for n in range(size)]).alias("x"))
    right = sketches.select(F.col("i").alias("j"), F.array(*[f"h{n}" for n in range(size)]).alias("y"))
    rows = pairs.select("i", "j", "ci", "cj").join(left, "i").join(right, "j")
    equal = F.expr("size(filter(zip_with(x, y, (p, q) -> p = q), z -> z))")
    jaccard = rows.withColumn("est_jaccard", equal / F.lit(float(size)))
    inter = "(est_jaccard * (CAST(ci AS DOUBLE) + CAST(cj AS DOUBLE)) / (1e0 + est_jaccard))"
    sim = of.sim(inter, "CAST(ci AS DOUBLE)", "CAST(cj AS DOUBLE)", "CAST(m AS DOUBLE)")
    scored = with_transactions(jaccard, m if of.uses_m else None).withColumn("est_sim", F.expr(sim))
    return scored.where(F.col("est_sim") >= delta - 1e-12).select("i", "j", F.round("est_jaccard", 6).alias("est_jaccard"), F.round("est_sim", 6).alias("est_sim"))


def filter_smaller_set(pairs: DataFrame, baskets: DataFrame, rate: float, measure: str | Measure, delta: float, m: DataFrame | None = None, seed: int = 7) -> DataFrame:
    """(i, j, probes, hits, est_sim): a sample of the rows of i is looked up in those of j; for measures of very unequal sets."""
    of = get(measure)
    thin = baskets.where(f"{draws.uniform_sql('t', seed)} < {rate!r}D")
    probes = pairs.select("i", "j", "ci", "cj").join(thin, "i").join(baskets.select("t", F.col("i").alias("j"), F.lit(1).alias("hit")), ["t", "j"], "left")
    counted = probes.groupBy("i", "j").agg(F.count("*").alias("probes"), F.count("hit").alias("hits"), F.first("ci").alias("ci"), F.first("cj").alias("cj"))
    inter = "(CAST(hits AS DOUBLE) / CAST(probes AS DOUBLE) * CAST(ci AS DOUBLE))"
    sim = of.sim(inter, "CAST(ci AS DOUBLE)", "CAST(cj AS DOUBLE)", "CAST(m AS DOUBLE)")
    scored = with_transactions(counted, m if of.uses_m else None).withColumn("est_sim", F.expr(sim))
    return scored.where(F.col("est_sim") >= delta - 1e-12).select("i", "j", "probes", "hits", F.round("est_sim", 6).alias("est_sim"))


def sampled_smaller_set(baskets: DataFrame, rate: float, measure: str | Measure, mu: float, delta: float, seed: int = 42, probe_seed: int = 7, strips: int | None = None) -> DataFrame:
    """``filter_smaller_set`` of the sampled pairs in one pass: samples and hits are counted where the occurrences of a pair are, and no pair is shuffled.

    The probes of i are the same for all its pairs: the sampled transactions that hold it.
    """
    from pairsample.operators.sampling import sample_pairs

    of = get(measure)
    items = numbered(baskets, MAX_ITEMS)
    if items is None:
        m = transactions(baskets) if of.uses_m else None
        return filter_smaller_set(sample_pairs(baskets, of, mu, delta, seed), baskets, rate, of, delta, m, probe_seed)
    m, uniform = _m(baskets, of), draws.uniform_sql("t", probe_seed)
    counts = baskets.where(f"{uniform} < {rate!r}D").groupBy("i").agg(F.count("*").alias("probes")).toArrow()
    probes = np.zeros(items.num_rows, np.int64)
    probes[pc.index_in(counts["i"], value_set=items["i"].combine_chunks()).to_numpy()] = counts["probes"].to_numpy()
    kind = baskets.schema["i"].dataType.simpleString()
    context = baskets.sparkSession.sparkContext
    names, known = context.broadcast(items["i"].combine_chunks()), context.broadcast(probes)

    def made(f: Found) -> Iterator[pa.RecordBatch]:
        r, u = (x[f.of] for x in f.strip.fixed)
        k = np.add.reduceat(np.repeat(of.array(f.ci, f.cj, delta, m) * mu, f.k) > r, f.begin, dtype=np.int64)
        hits = np.add.reduceat(u < rate, f.begin, dtype=np.int64)
        at = np.flatnonzero((k > 0) & (known.value[f.i] > 0))
        hit, probed, ci = hits[at], known.value[f.i[at]], f.ci[at]
        z = similarity(of, hit.astype(np.float64) / probed.astype(np.float64) * ci, ci, f.cj[at], m)
        near = np.flatnonzero(z >= delta - 1e-12)
        yield from named(names, {"i": f.i[at[near]], "j": f.j[at[near]], "probes": probed[near], "hits": hit[near], "est_sim": z[near]})

    rows = over_strips(baskets, items, made, f"i {kind}, j {kind}, probes long, hits long, est_sim double", (draws.draw_sql(seed), uniform), strips=strips)
    return rows.select("i", "j", "probes", "hits", F.round("est_sim", 6).alias("est_sim"))


def sampled_minhash(baskets: DataFrame, size: int, measure: str | Measure, mu: float, delta: float, seed: int = 42, width: int | None = None) -> DataFrame:
    """``filter_minhash`` of the sampled pairs, each tested by its sketches in the tile that counts it, so that no pair is shuffled."""
    from pairsample.operators.sampling import sample_pairs

    of = get(measure)
    items, sketches = numbered(baskets), minhash_sketch(baskets, size)
    if items is None:
        return filter_minhash(sample_pairs(baskets, of, mu, delta, seed), sketches, size, of, delta, transactions(baskets) if of.uses_m else None)
    m = _m(baskets, of)
    found = sketches.toArrow()
    place = pc.index_in(found["i"], value_set=items["i"].combine_chunks()).to_numpy()
    # values lie below 2^31
    values = np.empty((size, items.num_rows), np.int32)
    for n in range(size):
        values[n, place] = found[f"h{n}"].to_numpy()
    kind = baskets.schema["i"].dataType.simpleString()
    context = baskets.sparkSession.sparkContext
    names, known = context.broadcast(items["i"].combine_chunks()), context.broadcast(values)

    def made(i, j, ci, cj, k) -> Iterator[pa.RecordBatch]:
        equal = np.zeros(len(i), np.int32)
        for row in known.value:
            equal += row[i] == row[j]
        jaccard = equal / float(size)
        z = similarity(of, jaccard * (ci + cj) / (1.0 + jaccard), ci, cj, m)
        near = np.flatnonzero(z >= delta - 1e-12)
        yield from named(names, {"i": i[near], "j": j[near], "est_jaccard": jaccard[near], "est_sim": z[near]})

    rows = over_tiles(baskets, items, made, f"i {kind}, j {kind}, est_jaccard double, est_sim double", (of, mu, delta, seed, m), width)
    return rows.select("i", "j", F.round("est_jaccard", 6).alias("est_jaccard"), F.round("est_sim", 6).alias("est_sim"))
