"""Biased pair sampling: a pair (i, j) of a transaction is taken if f(ci, cj, delta) * mu exceeds the transaction's draw.

Items of a transaction are ordered by support, then by name; as f falls along that order, the partners taken for an item are a prefix of
those after it. All forms give the same sample for the same seed: ``prefix`` searches packed arrays inside the engine, ``arrow`` does the same for a whole
batch of transactions at once, ``shuffle`` keeps no transaction packed, ``blocked`` splits giant transactions over tasks, ``selfjoin`` tests every pair; ``tiles`` counts
pairs where they are made, so that none is shuffled (beyond a million items it is ``arrow``).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pairsample.functions import draws
from pairsample.functions.measures import Measure, dbl, get
from pairsample.operators.baskets import enrich, support_counts, transactions

STRATEGIES = ("arrow", "prefix", "shuffle", "blocked", "selfjoin", "tiles")


def drawn(enriched: DataFrame, seed: int, scope: str = "transaction") -> DataFrame:
    """Adds the draw r."""
    return enriched.withColumn("r", F.expr(draws.draw_sql(seed, scope)))


def with_m(rows: DataFrame, baskets: DataFrame, measure: Measure) -> DataFrame:
    """Adds m, the number of transactions, as a column; a single row is joined only where the measure needs it."""
    return rows.crossJoin(F.broadcast(transactions(baskets))) if measure.uses_m else rows.withColumn("m", F.lit(1).cast("long"))


def pack(rows: DataFrame) -> DataFrame:
    """(t, r, m, n, a): each transaction as one array of (c, i) in order."""
    return rows.groupBy("t").agg(F.first("r").alias("r"), F.first("m").alias("m"), F.array_sort(F.collect_list(F.struct("c", "i"))).alias("a")).withColumn("n", F.size("a"))


def ordered(enriched: DataFrame) -> DataFrame:
    """(t, i, c, place): the order inside each transaction as rows, by one sort on a packed key."""
    return enriched.withColumn("place", F.row_number().over(Window.partitionBy("t").orderBy("c", "i")))


def searched(packed: DataFrame, measure: Measure, mu: float, delta: float) -> DataFrame:
    """(t, n, a, f): for each place p of a transaction but the last one the last place that it is sampled with, by binary search."""
    test = f"{measure.weight_sql(delta, 'a[p - 1].c', 'a[mid - 1].c')} * {dbl(mu)} > r"
    search = (
        "transform(sequence(1, n - 1), p -> aggregate(sequence(1, CAST(ceil(log2(n + 1)) AS INT)), named_struct('lo', p, 'hi', n), "
        "(s, x) -> IF(s.lo >= s.hi, s, element_at(transform(array((s.lo + s.hi + 1) DIV 2), "
        f"mid -> IF({test}, named_struct('lo', CAST(mid AS INT), 'hi', s.hi), named_struct('lo', s.lo, 'hi', CAST(mid - 1 AS INT)))), 1)), s -> named_struct('p', p, 'last', s.lo)))"
    )
    return packed.where("n > 1").select("t", "n", "a", F.explode(F.expr(search)).alias("f"))


def prefix_pairs(packed: DataFrame, measure: Measure, mu: float, delta: float) -> DataFrame:
    """Sampled pairs (t, i, j, ci, cj) by a binary search for each item over the array of its transaction."""
    found = searched(packed, measure, mu, delta).where("f.last > f.p")
    pairs = found.select("t", F.expr("a[f.p - 1]").alias("x"), F.explode(F.expr("slice(a, f.p + 1, f.last - f.p)")).alias("y"))
    return pairs.select("t", F.col("x.i").alias("i"), F.col("y.i").alias("j"), F.col("x.c").alias("ci"), F.col("y.c").alias("cj"))


def count_tests(packed: DataFrame, measure: Measure, mu: float, delta: float) -> DataFrame:
    """One row: pairs of all transactions, sampled ones, and the tests of a scan that leaves an item at its first miss."""
    rows = searched(packed, measure, mu, delta)
    return rows.agg(
        F.sum(F.expr("CAST(n - f.p AS BIGINT)")).alias("pairs"), F.sum(F.expr("CAST(f.last - f.p AS BIGINT)")).alias("inserted"),
        F.sum(F.expr("CAST(least(n - f.p, f.last - f.p + 1) AS BIGINT)")).alias("tests_with_stop"),
    )


def last_admitted(c: np.ndarray, ends: np.ndarray, r: np.ndarray, m, measure: Measure, mu: float, delta: float) -> np.ndarray:
    """For each row of ordered transactions laid one after another, the last row whose item it is sampled with; itself if none.

    ``ends`` holds the last row of each row's transaction. One binary search for all rows together.
    """
    lo, hi = np.arange(len(c)), ends.copy()
    c = c.astype(np.float64)
    with np.errstate(divide="ignore"):
        while True:
            open_ = np.flatnonzero(lo < hi)
            if not len(open_):
                return lo
            mid = (lo[open_] + hi[open_] + 1) // 2
            yes = measure.array(c[open_], c[mid], delta, m if np.isscalar(m) else m[open_]) * mu > r[open_]
            lo[open_] = np.where(yes, mid, lo[open_])
            hi[open_] = np.where(yes, hi[open_], mid - 1)


def _counted(items: pa.Array, c: np.ndarray, first: np.ndarray, last: np.ndarray, room: int) -> Iterator[pa.RecordBatch]:
    """Pairs from each row to the rows after it up to ``last``, counted within chunks of about ``room`` pairs."""
    sizes = last - first
    codes = items.dictionary_encode()
    code, names = codes.indices.to_numpy(zero_copy_only=False).astype(np.int64), codes.dictionary
    # supports belong to items, so one row of each stands for it
    support = np.zeros(len(names), np.int64)
    support[code] = c
    at = np.cumsum(sizes)
    begin = 0
    while begin < len(first):
        end = max(begin + 1, int(np.searchsorted(at, (at[begin - 1] if begin else 0) + room, side="right")))
        x = np.repeat(first[begin:end], sizes[begin:end])
        y = x + 1 + np.arange(len(x)) - np.repeat(np.cumsum(sizes[begin:end]) - sizes[begin:end], sizes[begin:end])
        pair, k = np.unique(code[x] * len(names) + code[y], return_counts=True)
        a, b = pair // max(len(names), 1), pair % max(len(names), 1)
        if len(pair):
            yield pa.RecordBatch.from_arrays([names.take(pa.array(a)), names.take(pa.array(b)), pa.array(support[a]), pa.array(support[b]), pa.array(k.astype(np.int64))], names=["i", "j", "ci", "cj", "k"])
        begin = end


def arrow_counts(packed: DataFrame, measure: Measure, mu: float, delta: float, room: int = 2_000_000) -> DataFrame:
    """Partial counts (i, j, ci, cj, k) of sampled pairs, by one vectorised search over all transactions of a batch."""
    kind = packed.schema["a"].dataType.elementType["i"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(0)
            sizes = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
            flat = lists.flatten()
            if not len(flat):
                continue
            c = flat.field("c").to_numpy(zero_copy_only=False)
            r, m = (np.repeat(batch.column(x).to_numpy(zero_copy_only=False), sizes) for x in (1, 2))
            last = last_admitted(c, np.repeat(np.cumsum(sizes) - 1, sizes), r, m.astype(np.float64), measure, mu, delta)
            yield from _counted(flat.field("i"), c, np.arange(len(c)), last, room)

    return packed.where("n > 1").select("a", "r", "m").mapInArrow(run, f"i {kind}, j {kind}, ci long, cj long, k long")


def shuffle_counts(rows: DataFrame, measure: Measure, mu: float, delta: float, room: int = 2_000_000) -> DataFrame:
    """The same from rows sorted by (t, c, i) inside partitions of t: a transaction that a batch cuts goes on in the next one."""
    kind = rows.schema["i"].dataType.simpleString()
    sorted_ = rows.repartition("t").sortWithinPartitions("t", "c", "i").select("t", "i", "c", "r", "m")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def whole(table: pa.Table) -> Iterator[pa.RecordBatch]:
            t = table["t"].combine_chunks()
            if not len(t):
                return
            code = t.dictionary_encode().indices.to_numpy(zero_copy_only=False)
            starts = np.append(True, code[1:] != code[:-1])
            sizes = np.diff(np.append(np.flatnonzero(starts), len(code)))
            c, r, m = (table[x].to_numpy() for x in ("c", "r", "m"))
            last = last_admitted(c, np.repeat(np.cumsum(sizes) - 1, sizes), r, m.astype(np.float64), measure, mu, delta)
            yield from _counted(table["i"].combine_chunks(), c, np.arange(len(c)), last, room)

        kept: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            t = batch.column(0)
            final = t[len(t) - 1]
            # rows of the last transaction wait, as more of it may follow
            cut = pc.index(t, final).as_py()
            if cut:
                yield from whole(pa.Table.from_batches([*kept, batch.slice(0, cut)]))
                kept = [batch.slice(cut)]
            elif kept and kept[0].column(0)[0] != final:
                yield from whole(pa.Table.from_batches(kept))
                kept = [batch]
            else:
                kept.append(batch)
        if kept:
            yield from whole(pa.Table.from_batches(kept))

    return sorted_.mapInArrow(run, f"i {kind}, j {kind}, ci long, cj long, k long")


def blocked_pairs(rows: DataFrame, measure: Measure, mu: float, delta: float, block: int = 4096) -> DataFrame:
    """The same for transactions of any size: blocks of ``block`` items meet only if the pair of their smallest supports is taken."""
    placed = ordered(rows).withColumn("block", F.floor((F.col("place") - 1) / block))
    corner = placed.groupBy("t", "block").agg(F.min("c").alias("least"), F.first("r").alias("r"), F.first("m").alias("m"))
    test = f"{measure.weight_sql(delta, 'least', 'other_least')} * {dbl(mu)} > r"
    other = corner.select("t", F.col("block").alias("other"), F.col("least").alias("other_least"))
    meets = corner.join(other, "t").where("block <= other").where(test).select("t", "block", "other")
    left = placed.select("t", "block", "r", "m", F.col("place").alias("p"), F.col("i"), F.col("c").alias("ci"))
    right = placed.select("t", F.col("block").alias("other"), F.col("place").alias("q"), F.col("i").alias("j"), F.col("c").alias("cj"))
    pairs = meets.join(left, ["t", "block"]).join(right, ["t", "other"]).where("p < q")
    return pairs.where(f"{measure.weight_sql(delta)} * {dbl(mu)} > r").select("t", "i", "j", "ci", "cj")


def selfjoin_pairs(rows: DataFrame, measure: Measure, mu: float, delta: float) -> DataFrame:
    """The quadratic form: every pair of every transaction is tested."""
    left = rows.select("t", "r", "m", "i", F.col("c").alias("ci"))
    right = rows.select("t", F.col("i").alias("j"), F.col("c").alias("cj"))
    return left.join(right, "t").where("ci < cj OR (ci = cj AND i < j)").where(f"{measure.weight_sql(delta)} * {dbl(mu)} > r").select("t", "i", "j", "ci", "cj")


def count_pairs(pairs: DataFrame) -> DataFrame:
    """(i, j, k, ci, cj); rows are summed per task before they are shuffled."""
    k = F.sum("k") if "k" in pairs.columns else F.count("*")
    return pairs.groupBy("i", "j").agg(k.alias("k"), F.first("ci").alias("ci"), F.first("cj").alias("cj"))


def sample_rows(baskets: DataFrame, measure: str | Measure, seed: int = 42, scope: str = "transaction", support: DataFrame | None = None) -> DataFrame:
    """(t, i, c, r, m): what every form starts from."""
    return with_m(drawn(enrich(baskets, support), seed, scope), baskets, get(measure))


def sample_pairs(
    baskets: DataFrame, measure: str | Measure = "cosine", mu: float = 15.0, delta: float = 0.5, seed: int = 42,
    strategy: str = "arrow", scope: str = "transaction", block: int = 4096, support: DataFrame | None = None,
) -> DataFrame:
    """The sampled multiset as (i, j, k, ci, cj), i being the item of smaller support (of equal ones the smaller).

    ``scope='anchor'`` draws for each item of a transaction instead of once for all; it needs ``selfjoin`` or ``blocked``.
    """
    of = get(measure)
    if strategy == "tiles" and scope == "transaction" and support is None:
        from pairsample.operators import tiles

        items = tiles.numbered(baskets)
        if items is not None:
            return tiles.tile_sample(baskets, items, of, mu, delta, seed)
    rows = sample_rows(baskets, of, seed, scope, support)
    if scope == "anchor" and strategy not in ("selfjoin", "blocked"):
        raise ValueError("one draw for each item isn't kept in packed transactions; take 'selfjoin' or 'blocked'")
    if strategy == "shuffle":
        counted = support_counts(baskets, "sort")
        return count_pairs(shuffle_counts(with_m(drawn(counted, seed), baskets, of), of, mu, delta))
    if strategy == "prefix":
        return count_pairs(prefix_pairs(pack(rows), of, mu, delta))
    if strategy == "blocked":
        return count_pairs(blocked_pairs(rows, of, mu, delta, block))
    if strategy == "selfjoin":
        return count_pairs(selfjoin_pairs(rows, of, mu, delta))
    return count_pairs(arrow_counts(pack(rows), of, mu, delta))
