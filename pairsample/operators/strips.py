"""Co-occurrences over strips of items, for many items or for what looks at single occurrences: no pair is shuffled.

Items are numbered as for tiles and cut into strips of about equal work. A strip gets, of each transaction that holds items of it, the items from the
first of these on, so that it can make all pairs whose first item is its own. They are made anchor by anchor, sorted, and handed on with their occurrences.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.functions.measures import Measure, get
from pairsample.operators import tiles
from pairsample.operators.tiles import similarity

#: Items up to which their numbers are held by every task, and up to which they are joined without a shuffle.
MAX_ITEMS, BROADCAST_ITEMS = 4_000_000, 1_000_000
#: Pairs made at once, and items of transactions dealt at once.
ROOM, DEALT = 1 << 21, 500_000
#: Items that a strip holds, by estimate: beyond that there are more strips, each row being sent to more of them.
HELD = 1 << 26
_BINARY = ("sizes", "anchors", "items", "fixed", "drawn", "seeds", "values")


class Found(NamedTuple):
    """Some pairs of a strip: numbers, supports, counts, and their occurrences, those of pair p being ``of[begin[p]:begin[p] + k[p]]`` among the lists of the strip."""

    i: np.ndarray
    j: np.ndarray
    ci: np.ndarray
    cj: np.ndarray
    k: np.ndarray
    begin: np.ndarray
    of: np.ndarray
    strip: Strip


class Strip:
    """The lists of one strip: ``fixed`` draws of each (lists, draws), and the draws of ``seeds`` that are small enough to take a pair."""

    def __init__(self, parts: dict[str, list[bytes]], fixed: int) -> None:
        whole = {x: b"".join(parts[x]) for x in _BINARY}
        self.sizes, self.anchors = (np.frombuffer(whole[x], "<u4").astype(np.int64) for x in ("sizes", "anchors"))
        self.items = np.frombuffer(whole["items"], "<u4")
        # each part holds its draws column by column
        self.fixed = np.concatenate([np.frombuffer(x, np.float64).reshape(fixed, -1) for x in parts["fixed"]], axis=1) if fixed else np.zeros((0, len(self.sizes)))
        drawn, seeds = np.frombuffer(whole["drawn"], "<u2").astype(np.int64), np.frombuffer(whole["seeds"], "<u2")
        order = np.argsort(seeds, kind="stable")
        self._of, self._value = np.repeat(np.arange(len(drawn)), drawn)[order], (np.frombuffer(whole["values"], "<u4") / 4294967296.0)[order]
        self._ends = np.cumsum(np.bincount(seeds, minlength=1 << 16))

    def draw(self, seed: int) -> np.ndarray:
        """The draw of a seed for each list; 2 where it is too large to take any pair."""
        out = np.full(len(self.sizes), 2.0)
        part = slice(int(self._ends[seed - 1]) if seed else 0, int(self._ends[seed]))
        out[self._of[part]] = self._value[part]
        return out

    def pairs(self, c: np.ndarray, room: int = ROOM) -> Iterator[Found]:
        of = np.repeat(np.arange(len(self.sizes)), self.anchors)
        starts, ends = np.cumsum(self.sizes) - self.sizes, np.cumsum(self.sizes)
        at = np.arange(len(of)) - np.repeat(np.cumsum(self.anchors) - self.anchors, self.anchors) + starts[of]
        after = ends[of] - at - 1
        keep = np.flatnonzero(after > 0)
        keep = keep[np.argsort(self.items[at[keep]], kind="stable")]
        of, at, after = of[keep], at[keep], after[keep]
        anchor = self.items[at].astype(np.int64)
        # whole anchors, as many as make about ``room`` pairs
        first = np.flatnonzero(np.append(True, anchor[1:] != anchor[:-1])) if len(anchor) else np.zeros(0, np.int64)
        work = np.append(np.cumsum(after), 0)[np.append(first[1:], len(anchor)) - 1] if len(first) else first
        begin = 0
        while begin < len(first):
            end = max(begin + 1, int(np.searchsorted(work, (work[begin - 1] if begin else 0) + room, side="right")))
            rows = slice(int(first[begin]), int(first[end]) if end < len(first) else len(anchor))
            yield self._made(c, of[rows], at[rows], after[rows], anchor[rows])
            begin = end

    def _made(self, c: np.ndarray, of: np.ndarray, at: np.ndarray, after: np.ndarray, anchor: np.ndarray) -> Found:
        total = int(after.sum())
        other = self.items[np.repeat(at + 1 - (np.cumsum(after) - after), after) + np.arange(total)]
        low, span = anchor[0], len(c)
        key = np.repeat((anchor - low) * span, after) + other
        bits = max(1, total.bit_length())
        if (int(anchor[-1] - low + 1) * span).bit_length() + bits < 63:
            # the place of an occurrence is kept in the low bits, as plain numbers are sorted faster than their places
            key = key << bits | np.arange(total)
            key.sort()
            place, key = key & ((1 << bits) - 1), key >> bits
        else:
            place = np.argsort(key, kind="stable")
            key = key[place]
        begin = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
        i, j = key[begin] // span + low, key[begin] % span
        return Found(i, j, c[i], c[j], np.diff(np.append(begin, total)), begin, np.repeat(of, after)[place], self)


def seed_draws(texts: list[bytes], seeds: range) -> np.ndarray:
    """(seeds, texts): the first 32 bits of the MD5 of ``seed:text``."""
    md5, out = hashlib.md5, np.empty((len(seeds), len(texts)), np.uint32)
    for n, seed in enumerate(seeds):
        head = b"%d:" % seed
        out[n] = np.frombuffer(b"".join([md5(head + t).digest() for t in texts]), ">u4")[::4]
    return out


def _taking(batch: pa.RecordBatch, c: np.ndarray, chance: Callable) -> pa.RecordBatch:
    """The transactions whose first draw is below the chance of the pair of their two smallest supports: others take no pair."""
    lists = batch.column(0)
    sizes = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
    key = np.repeat(np.arange(len(sizes)), sizes) << 32 | lists.flatten().to_numpy().astype(np.int64)
    key.sort()
    head = np.cumsum(sizes) - sizes
    most = chance(c[key[head] & 0xFFFFFFFF], c[key[head + 1] & 0xFFFFFFFF])
    return batch.filter(pa.array(most > batch.column(2).to_numpy(zero_copy_only=False)))


def _deal(sent, cuts: np.ndarray, fixed: int, seeds: range, chance: Callable | None) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Transactions (a, t, draws) to rows (strip, ...) as Strip reads them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = sent.value
        for batch in (part for whole in batches for part in tiles._slices(whole, DEALT)):
            if fixed and chance is not None:
                batch = _taking(batch, c, chance)
            if not batch.num_rows:
                continue
            lists = batch.column(0)
            sizes = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
            key = np.repeat(np.arange(len(sizes)), sizes) << 32 | lists.flatten().to_numpy().astype(np.int64)
            key.sort()
            of, item = key >> 32, key & 0xFFFFFFFF
            ends = np.cumsum(sizes)
            drawn = np.zeros(len(sizes), np.int64)
            if len(seeds):
                head = ends - sizes
                most = chance(c[item[head]], c[item[head + 1]])
                value = seed_draws([t.encode() for t in batch.column(1).to_pylist()], seeds)
                who, which = np.nonzero((value / 4294967296.0 < most[None, :]).T)
                value, drawn = value[which, who], np.bincount(who, minlength=len(sizes))
                which = which + seeds[0]
            values = [batch.column(2 + n).to_numpy(zero_copy_only=False) for n in range(fixed)]
            strip = np.searchsorted(cuts, item, side="right") - 1
            begin = np.flatnonzero(np.append(True, (of[1:] != of[:-1]) | (strip[1:] != strip[:-1])))
            anchors = np.diff(np.append(begin, len(item)))
            whose, at = of[begin], strip[begin]
            left = ends[whose] - begin
            out = []
            for x in np.unique(at[left > 1]).tolist():
                rows = np.flatnonzero((at == x) & (left > 1))
                n, t = left[rows], whose[rows]
                places = np.repeat(begin[rows] - (np.cumsum(n) - n), n) + np.arange(n.sum())
                row = [x, n.astype("<u4").tobytes(), anchors[rows].astype("<u4").tobytes(), item[places].astype("<u4").tobytes(), b"".join([v[t].tobytes() for v in values])]
                row += [drawn[t].astype("<u2").tobytes(), b"", b""]
                if len(seeds):
                    d = drawn[t]
                    places = np.repeat((np.cumsum(drawn) - drawn)[t] - (np.cumsum(d) - d), d) + np.arange(d.sum())
                    row[-2:] = which[places].astype("<u2").tobytes(), value[places].astype("<u4").tobytes()
                out.append(row)
            if out:
                kinds = (pa.int32(), *[pa.binary()] * len(_BINARY))
                yield pa.RecordBatch.from_arrays([pa.array(col, kind) for col, kind in zip(zip(*out, strict=True), kinds, strict=True)], names=["strip", *_BINARY])

    return run


def _cuts(c: np.ndarray, rows: float, m: float, strips: int) -> np.ndarray:
    """The first item of each strip: the work of an item is its support times what stands after it in a transaction, as if items were independent."""
    after = (rows - np.cumsum(c)) / max(m, 1.0)
    work = np.cumsum(c * (after + 0.5))
    if work[-1] and rows / 2 > HELD:
        strips = max(strips, int(np.ceil(work[-1] / HELD)))
    cuts = np.searchsorted(work, work[-1] * np.arange(strips) / strips, side="right")
    cuts[0] = 0
    return np.unique(np.minimum(cuts, len(c) - 1))


def over_strips(
    baskets: DataFrame, items: pa.Table, made: Callable[[Found], Iterator[pa.RecordBatch]], schema: str, fixed: tuple[str, ...] = (), seeds: range = range(0),
    chance: Callable | None = None, strips: int | None = None,
) -> DataFrame:
    """What ``made`` yields for the pairs of all strips.

    ``fixed`` are SQL texts of numbers of each transaction t; with ``chance`` only transactions take part that may take a pair by the first of them.
    With ``seeds`` the lists have a draw for each, kept where it is below ``chance`` of the supports of a transaction's first pair.
    """
    context = baskets.sparkSession.sparkContext
    c = items["c"].to_numpy().astype(np.float64)
    if not len(c):
        return baskets.sparkSession.createDataFrame([], schema)
    m = float(baskets.agg(F.count_distinct("t")).first()[0]) if c.sum() / 2 > HELD else 1.0
    cuts = _cuts(c, float(c.sum()), m, strips or max(8, 2 * context.defaultParallelism))
    sent, n = context.broadcast(c), len(fixed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: dict[str, list[bytes]] = {x: [] for x in _BINARY}
        for batch in batches:
            for x in _BINARY:
                parts[x] += batch.column(x).to_pylist()
        if parts["sizes"]:
            strip = Strip(parts, n)
            parts.clear()
            for found in strip.pairs(sent.value):
                yield from made(found)

    table = baskets.sparkSession.createDataFrame(pa.table({"i": items["i"], "n": np.arange(len(c), dtype=np.int32)}), f"i {baskets.schema['i'].dataType.simpleString()}, n int")
    rows = baskets.join(F.broadcast(table) if len(c) <= BROADCAST_ITEMS else table, "i").groupBy("t").agg(F.collect_list("n").alias("a")).where("size(a) > 1")
    rows = rows.select("a", F.col("t").cast("string") if len(seeds) else F.lit("").alias("t"), *[F.expr(x).alias(f"f{k}") for k, x in enumerate(fixed)])
    dealt = rows.mapInArrow(_deal(sent, cuts, n, seeds, chance), ", ".join(["strip int", *[f"{x} binary" for x in _BINARY]]))
    return dealt.repartitionById(len(cuts), F.col("strip")).mapInArrow(run, schema)


def named(sent, columns: dict[str, np.ndarray]) -> Iterator[pa.RecordBatch]:
    """Rows of pairs with their names in place of the numbers i and j."""
    for at in range(0, len(columns["i"]), 100_000):
        to = slice(at, at + 100_000)
        yield pa.RecordBatch.from_arrays([sent.value.take(pa.array(v[to])) if x in ("i", "j") else pa.array(v[to]) for x, v in columns.items()], names=list(columns))


def strip_pairs(baskets: DataFrame, items: pa.Table, measure: str | Measure | None = None, delta: float = 0.0, strips: int | None = None) -> DataFrame:
    """(i, j, k, ci, cj) of the co-occurring pairs; with a measure only of those whose similarity may reach ``delta``."""
    of = get(measure) if measure is not None else None
    m = tiles._m(baskets, of)
    kind = baskets.schema["i"].dataType.simpleString()
    sent = baskets.sparkSession.sparkContext.broadcast(items["i"].combine_chunks())

    def made(f: Found):
        near = np.flatnonzero(similarity(of, f.k.astype(np.float64), f.ci, f.cj, m) >= delta - 1e-9) if of is not None else slice(None)
        yield from named(sent, {"i": f.i[near], "j": f.j[near], "k": f.k[near], "ci": f.ci[near].astype(np.int64), "cj": f.cj[near].astype(np.int64)})

    return over_strips(baskets, items, made, f"i {kind}, j {kind}, k long, ci long, cj long", strips=strips)


def strip_sums(baskets: DataFrame, items: pa.Table, measure: str | Measure, mu: float, delta: float, strips: int | None = None) -> DataFrame:
    """The partial sums of ``tile_sums``."""
    of = get(measure)
    sums = tiles.sums_of(of, tiles._m(baskets, of), mu, delta)
    return over_strips(baskets, items, lambda f: sums(f.i, f.j, f.ci, f.cj, f.k), tiles.SUMS, strips=strips)
