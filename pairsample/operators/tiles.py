"""Co-occurrence counts over tiles of the pair matrix, so that no pair is shuffled.

Items are numbered in the order of their supports and cut into runs of whole blocks; a tile is a pair of runs. Each tile gets the items that
transactions hold of both runs, as packed numbers of two bytes, and counts its pairs block by block, each pair of blocks in one dense array. A pair is so
counted in one place, and what is made of the counts (a filter, a sum) is done there. Long transactions are counted together by a matrix product; of a
sample only the partners that an item takes are looked at, which are those up to a place in the order of supports.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.functions import draws
from pairsample.functions.measures import Measure, get
from pairsample.operators.baskets import support_counts, transactions
from pairsample.operators.held import release

#: Items of a block at most, and how many runs items are dealt over about, so that there are tiles enough for all tasks and each row is sent only so often.
WIDTH, RUNS = 4096, 8
#: Items of a run at most, as their numbers have two bytes.
RUN = 1 << 16
#: Items up to which their numbers are held by every task.
MAX_ITEMS = 1_000_000
#: Rows beyond which the shuffle files of the supports are not left to chance.
RELEASED = 1_000_000
#: Pairs made at once, and items of transactions dealt at once.
ROOM, DEALT = 1_000_000, 1_000_000
#: Rows of a block that ``made`` gets at once.
ROWS = 64
#: A transaction that fills more than this share of a tile is counted by the matrix product, so many at once.
FULL, TOGETHER = 1 / 300, 256
_NUMPY = {"sqrt": np.sqrt, "greatest": np.maximum, "least": np.minimum}


def evaluate(text: str, **operands) -> np.ndarray:
    """A measure's SQL text over arrays of doubles: the same steps as in the engine."""
    return eval(text, {"__builtins__": {}}, {**_NUMPY, **operands})  # noqa: S307


def similarity(of: Measure, k: np.ndarray, ci: np.ndarray, cj: np.ndarray, m: float) -> np.ndarray:
    return evaluate(of.sim("k", "ci", "cj", "m"), k=k, ci=ci, cj=cj, m=m)


def numbered(baskets: DataFrame, max_items: int = MAX_ITEMS) -> pa.Table | None:
    """(i, c) of all items, by support and then by name; None if there are more than ``max_items``."""
    found = support_counts(baskets).limit(max_items + 1).toArrow()
    if (pc.sum(found["c"]).as_py() or 0) > RELEASED:
        release(baskets.sparkSession)
    return found.sort_by([("c", "ascending"), ("i", "ascending")]) if found.num_rows <= max_items else None


def _packed(baskets: DataFrame, items: pa.Table, seed: int | None) -> DataFrame:
    """(a, r): the item numbers of each transaction and its draw."""
    spark = baskets.sparkSession
    numbers = pa.table({"i": items["i"], "n": np.arange(items.num_rows, dtype=np.int32)})
    table = spark.createDataFrame(numbers, f"i {baskets.schema['i'].dataType.simpleString()}, n int")
    rows = baskets.join(F.broadcast(table), "i").groupBy("t").agg(F.collect_list("n").alias("a")).where("size(a) > 1")
    return rows.select("a", (F.expr(draws.draw_sql(seed)) if seed is not None else F.lit(0.0)).alias("r"))


def _slices(batch: pa.RecordBatch, room: int = ROOM) -> Iterator[pa.RecordBatch]:
    """The batch in parts of about ``room`` items, a longer transaction being a part of its own."""
    ends = np.cumsum(pc.list_value_length(batch.column(0)).to_numpy(zero_copy_only=False))
    begin = 0
    while begin < batch.num_rows:
        end = max(begin + 1, int(np.searchsorted(ends, (ends[begin - 1] if begin else 0) + room, side="right")))
        yield batch.slice(begin, end - begin)
        begin = end


def _deal(width: int, runs: int, most: np.ndarray | None = None, takes: Callable | None = None) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Transactions to rows (tile, sizes, left, right, r): what they hold of both runs of a tile, unless their draw is above all chances of the tile, ``most``.

    With ``takes(item, r, run)`` only the items that may be taken with one of the other run.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (part for whole in batches for part in _slices(whole, DEALT)):
            lists = batch.column(0)
            sizes = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
            key = np.repeat(np.arange(len(sizes)), sizes) << 32 | lists.flatten().to_numpy().astype(np.int64)
            key.sort()
            of, item = key >> 32, key & 0xFFFFFFFF
            at = item // width
            r = batch.column(1).to_numpy(zero_copy_only=False)

            def part(rows: np.ndarray, x: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
                return of[rows], (item[rows] - x * width).astype("<u2"), np.bincount(of[rows], minlength=len(sizes))

            owns = [np.flatnonzero(at == x) for x in range(runs)]
            parts = [part(own, x) for x, own in enumerate(owns)]
            out = []
            for x in range(runs):
                for y in range(x, runs):
                    if most is not None and most[tile_number(x, y)] < 0:
                        continue
                    (ofx, ix, nx), (ofy, iy, ny) = parts[x], parts[y]
                    if takes is not None:
                        (ofx, ix, nx), (ofy, iy, ny) = (part(owns[u][takes(item[owns[u]], r[of[owns[u]]], v)], u) for u, v in ((x, y), (y, x)))
                    both = (nx > 1) if x == y else (nx > 0) & (ny > 0)
                    if most is not None:
                        both &= r < most[tile_number(x, y)]
                    if both.any():
                        left, right = ix[both[ofx]].tobytes(), b"" if x == y else iy[both[ofy]].tobytes()
                        out.append((tile_number(x, y), np.stack([nx[both], ny[both]]).astype("<u4").tobytes(), left, right, r[both].tobytes()))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(zip(*out, strict=True), KINDS, strict=True)], names=["tile", "sizes", "left", "right", "r"])

    return run


KINDS = (pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.binary())


def tile_number(x: int, y: int) -> int:
    return y * (y + 1) // 2 + x


def tile_at(number: int) -> tuple[int, int]:
    y = 0
    while (y + 1) * (y + 2) // 2 <= number:
        y += 1
    return number - y * (y + 1) // 2, y


class Side:
    """What transactions hold of one run, block by block: the transactions, how many items, and these, numbered from the block's first."""

    def __init__(self, n: np.ndarray, items: np.ndarray, width: int, blocks: int) -> None:
        of, at = np.repeat(np.arange(len(n), dtype=np.int32), n), items // width
        self.blocks = []
        for b in range(blocks):
            own = np.flatnonzero(at == b)
            who = of[own]
            begin = np.flatnonzero(np.append(True, who[1:] != who[:-1])) if len(who) else np.zeros(0, np.int64)
            self.blocks.append((who[begin], np.diff(np.append(begin, len(who))).astype(np.uint32), items[own] - np.uint16(b * width)))

    def block(self, b: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        who, n, items = self.blocks[b]
        return who, n.astype(np.int64), items.astype(np.int64)


class Tile:
    """The counts of a pair of blocks; with ``chance``, that of arrays of supports, an occurrence counts only above the transaction's draw."""

    def __init__(self, cx: np.ndarray, cy: np.ndarray, chance: Callable | None, same: bool) -> None:
        self.shape, self.cx, self.cy, self.chance, self.same = (len(cx), len(cy)), cx, cy, chance, same
        self.least = None if chance is None else float(chance(cx[-1:], cy[-1:])[0])
        self.k = np.zeros(self.shape, np.int32)
        self.whole: list[tuple[np.ndarray, np.ndarray]] = []

    def add(self, nx: np.ndarray, ny: np.ndarray, left: np.ndarray, right: np.ndarray, r: np.ndarray) -> None:
        """Transactions one after another, the items of each in order."""
        atx, aty = np.cumsum(nx) - nx, np.cumsum(ny) - ny
        large = nx * ny > FULL * self.shape[0] * self.shape[1]
        if self.chance is not None:
            large &= self.least > r
        for t in np.flatnonzero(large):
            self.whole.append((left[atx[t] : atx[t] + nx[t]], right[aty[t] : aty[t] + ny[t]]))
            if len(self.whole) == TOGETHER:
                self.multiply()
        few = np.flatnonzero(~large)
        if not len(few):
            return
        # one row for each item of the left block, its partners being those of the right block, in one block those after it
        rows = np.repeat(atx[few] - (np.cumsum(nx[few]) - nx[few]), nx[few]) + np.arange(nx[few].sum())
        of = np.repeat(few, nx[few])
        first = (rows - atx[of] + aty[of] + 1) if self.same else aty[of]
        last = aty[of] + ny[of]
        if self.chance is not None:
            rows, first, last = self._taken(rows, first, last, left, right, r[of])
        n = last - first
        ends = np.cumsum(n)
        begin = 0
        while begin < len(rows):
            end = max(begin + 1, int(np.searchsorted(ends, (ends[begin - 1] if begin else 0) + ROOM, side="right")))
            some = n[begin:end]
            other = np.repeat(first[begin:end] - (np.cumsum(some) - some), some) + np.arange(some.sum())
            np.add.at(self.k.reshape(-1), np.repeat(left[rows[begin:end]] * self.shape[1], some) + right[other], 1)
            begin = end

    def _taken(self, rows: np.ndarray, first: np.ndarray, last: np.ndarray, left: np.ndarray, right: np.ndarray, r: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The rows that take any partner, and where these begin and end: as chances fall along the order, by one binary search for all."""
        c = self.cx[left[rows]]
        some = first < last
        some[some] = self.chance(c[some], self.cy[right[first[some]]]) > r[some]
        rows, first, last, c, r = (x[some] for x in (rows, first, last, c, r))
        lo, hi = first.copy(), last - 1
        while len(at := np.flatnonzero(lo < hi)):
            mid = (lo[at] + hi[at] + 1) // 2
            yes = self.chance(c[at], self.cy[right[mid]]) > r[at]
            lo[at], hi[at] = np.where(yes, mid, lo[at]), np.where(yes, hi[at], mid - 1)
        return rows, first, lo + 1

    def multiply(self) -> None:
        if self.whole:
            x, y = np.zeros((len(self.whole), self.shape[0]), np.float32), np.zeros((len(self.whole), self.shape[1]), np.float32)
            for n, (a, b) in enumerate(self.whole):
                x[n, a] = 1
                y[n, b] = 1
            for at in range(0, self.shape[0], 512):
                self.k[at : at + 512] += (x[:, at : at + 512].T @ y).astype(np.int32)
            self.whole = []


def over_tiles(
    baskets: DataFrame, items: pa.Table, made: Callable, schema: str, sample: tuple | None = None, width: int | None = None, reach: tuple | None = None,
) -> DataFrame:
    """What ``made(i, j, ci, cj, k)`` yields for the numbers, supports and counts of the pairs of some rows of a pair of blocks, all rows together.

    ``sample`` is (measure, mu, delta, seed, m) where only sampled occurrences count. With ``reach``, (measure, delta, m), blocks are left out in which no
    pair can reach delta, even if the item of smaller support were always with the other.
    """
    n = items.num_rows
    width = width or min(WIDTH, max(64, -(-n // RUNS)))
    many = max(1, min(RUN // width, -(-n // (width * RUNS))))
    wide = width * many
    runs = max(1, -(-n // wide))
    seed = sample[3] if sample else None
    supports = items["c"].to_numpy().astype(np.float64)
    sent = baskets.sparkSession.sparkContext.broadcast(supports)
    chance = None
    if sample:
        of, mu, delta, _, m = sample
        chance = lambda ci, cj: of.array(ci, cj, delta, m) * mu

    def may(cx: np.ndarray, cy: np.ndarray) -> bool:
        if reach is None:
            return True
        measure, at_least, m = reach
        # similarities rise with the count, which is the smaller support at most, and fall with the larger support
        return not similarity(measure, cx, cx, np.maximum(cx, cy[0]), m).max() * (1 + 1e-9) < at_least - 1e-9

    def counted(x: int, y: int, c: np.ndarray, held: list[tuple]) -> Iterator[pa.RecordBatch]:
        sizes = np.concatenate([np.frombuffer(row[0], "<u4").reshape(2, -1) for row in held], axis=1).astype(np.int64)
        r = np.frombuffer(b"".join([row[3] for row in held]), np.float64)
        sides = [Side(sizes[k], np.frombuffer(b"".join([row[k + 1] for row in held]), "<u2"), width, many) for k in range(1 if x == y else 2)]
        held.clear()
        for bx in range(many):
            who, nx, left = sides[0].block(bx)
            if not len(who):
                continue
            place = np.full(len(r), -1, np.int32)
            place[who] = np.arange(len(who))
            for by in range(bx if x == y else 0, many):
                first_x, first_y = x * wide + bx * width, y * wide + by * width
                cx, cy = c[first_x : first_x + width], c[first_y : first_y + width]
                if not len(cy) or not may(cx, cy):
                    continue
                other, ny, right = (who, nx, left) if first_x == first_y else sides[-1].block(by)
                met = place[other] >= 0
                if chance is not None:
                    met &= chance(cx[:1], cy[:1])[0] * (1 + 1e-9) > r[other]
                if not met.any():
                    continue
                also = np.zeros(len(who), bool)
                also[place[other[met]]] = True
                tile = Tile(cx, cy, chance, first_x == first_y)
                tile.add(nx[also], ny[met], left[np.repeat(also, nx)], right[np.repeat(met, ny)], r[other[met]])
                tile.multiply()
                for at in range(0, tile.shape[0], ROWS):
                    part = tile.k[at : at + ROWS]
                    if tile.same:
                        part = np.triu(part, at + 1)
                    i, j = np.nonzero(part)
                    if len(i):
                        k = part[i, j].astype(np.int64)
                        i, j = i + at + first_x, j + first_y
                        yield from made(i, j, c[i], c[j], k)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple]] = {}
        for batch in batches:
            for number, *row in zip(*[col.to_pylist() for col in batch.columns], strict=True):
                held.setdefault(number, []).append(row)
        for number in list(held):
            yield from counted(*tile_at(number), sent.value, held.pop(number))

    most = takes = None
    if n:
        at = np.array([tile_at(k) for k in range(runs * (runs + 1) // 2)])
        first = supports[::wide]
        if sample:
            # chances fall as supports grow, so the first items of both runs have the greatest
            most = chance(first[at[:, 0]], first[at[:, 1]]) * (1 + 1e-9)
            takes = lambda item, r, run: chance(sent.value[item], np.full(len(item), first[run])) * (1 + 1e-9) > r
        elif reach is not None:
            most = np.array([1.0 if may(supports[x * wide : (x + 1) * wide], supports[y * wide : (y + 1) * wide]) else -1.0 for x, y in at])
    dealt = _packed(baskets, items, seed).mapInArrow(_deal(wide, runs, most, takes), "tile int, sizes binary, left binary, right binary, r binary")
    return dealt.repartitionById(runs * (runs + 1) // 2, F.col("tile")).mapInArrow(run, schema)


def tile_pairs(baskets: DataFrame, items: pa.Table, measure: str | Measure | None = None, delta: float = 0.0, sample: tuple | None = None, width: int | None = None) -> DataFrame:
    """(i, j, k, ci, cj) of the co-occurring or sampled pairs; with a measure only of those whose similarity may reach ``delta``."""
    of = get(measure) if measure is not None else None
    m = _m(baskets, of)
    kind = baskets.schema["i"].dataType.simpleString()
    sent = baskets.sparkSession.sparkContext.broadcast(items["i"].combine_chunks())

    def made(i, j, ci, cj, k):
        if of is not None:
            near = similarity(of, k.astype(np.float64), ci, cj, m) >= delta - 1e-9
            i, j, ci, cj, k = (x[near] for x in (i, j, ci, cj, k))
        for at in range(0, len(i), 100_000):
            to = slice(at, at + 100_000)
            yield pa.RecordBatch.from_arrays([sent.value.take(pa.array(i[to])), sent.value.take(pa.array(j[to])), pa.array(k[to]), pa.array(ci[to].astype(np.int64)), pa.array(cj[to].astype(np.int64))], names=["i", "j", "k", "ci", "cj"])

    return over_tiles(baskets, items, made, f"i {kind}, j {kind}, k long, ci long, cj long", sample, width, (of, delta, m) if of is not None else None)


#: What ``sums_of`` yields.
SUMS = "inserted double, entries double, distinct_pairs long, output long, sum_sim double"


def sums_of(of: Measure, m: float, mu: float, delta: float) -> Callable:
    """Partial sums over co-occurring pairs: expected insertions and entries, pairs, pairs at or above delta, sum of similarities."""

    def made(i, j, ci, cj, k):
        z = similarity(of, k.astype(np.float64), ci, cj, m)
        p = np.minimum(1.0, of.array(ci, cj, delta, m) * mu)
        part = p < 1.0
        # a pair that is taken with certainty has one entry, and one that occurs once has one with its chance
        once = part & (k == 1)
        part &= ~once
        entries = float(len(p) - np.count_nonzero(part) - np.count_nonzero(once)) + float((1 - (1 - p[once])).sum()) + float((1 - np.power(1 - p[part], k[part])).sum())
        values = [float((k * p).sum()), entries, len(k), int(np.count_nonzero(z >= delta - 1e-12)), float(z.sum())]
        yield pa.RecordBatch.from_arrays([pa.array([v]) for v in values], names=["inserted", "entries", "distinct_pairs", "output", "sum_sim"])

    return made


def tile_sums(baskets: DataFrame, items: pa.Table, measure: str | Measure, mu: float, delta: float, width: int | None = None) -> DataFrame:
    """One row of ``sums_of`` for each part of a tile."""
    of = get(measure)
    return over_tiles(baskets, items, sums_of(of, _m(baskets, of), mu, delta), SUMS, None, width)


def tile_sample(baskets: DataFrame, items: pa.Table, measure: str | Measure, mu: float, delta: float, seed: int, width: int | None = None) -> DataFrame:
    """(i, j, k, ci, cj) of the sampled pairs, one draw for each transaction."""
    of = get(measure)
    return tile_pairs(baskets, items, sample=(of, mu, delta, seed, _m(baskets, of)), width=width)


def _m(baskets: DataFrame, of: Measure | None) -> float:
    return float(transactions(baskets).first()["m"]) if of is not None and of.uses_m else 1.0
