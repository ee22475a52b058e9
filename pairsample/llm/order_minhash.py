"""Near-duplicate texts by Order MinHash, verified by banded alignment.

A text is its sequence of lower-case words. Every run of ``k`` words is labelled with how many equal runs stand before it. Each of
several hash functions picks the ``picks`` smallest labelled runs and keeps them in text order; texts that agree in one
such list are candidates, more likely the smaller their edit distance, as order counts. The number of hash functions follows from the recall asked
for at the threshold. Texts of up to ``SHORT`` words have too few runs for that; they are candidates if they share one of their rarest words,
which loses nothing. Candidates are verified by the word-level edit distance inside a band: they are near if 1 - distance / longer length
reaches ``threshold``.

Groups may hold any share of the rows, so no group is expanded. Equal texts fall together first. In each bucket the smallest id leads, and a text
meets the one that leads most of its buckets; then, where the texts of a bucket are still in several components, the one with most links leads and
meets the others. What stays mixed after that is compared as far as components differ: buckets of little work by a join, larger ones over tiles of their
texts, each of which gives only links that connect what was apart. The texts of the largest buckets go on by
keys that every near pair shares and that grow more special step by step: one of the rarest words, then two, then three of them, as long as more keys
are less work than to compare a bucket. A pair may share many keys; it is made at the first that it has in common. Before it is aligned, a pair must pass bounds that no near pair
fails: the lengths, bitmaps of labelled words, and in tiles how many of these may be common. Verified links are closed to components.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairsample.llm.common import Scratch, components, components_of
from pairsample.llm.language_model import mix

BLOCK_CHARS = 600_000
#: Bins of the word counts that bound a distance from below.
BINS = 2048
#: Texts of up to so many words are matched by their rarest words instead of sketches.
SHORT = 50
#: Slots of the counts by which words are rare.
SLOTS = 1 << 16
#: Comparisons up to which a bucket is compared in full: by a join, and over tiles.
WORK, RARE_WORK = 256, 1 << 22
#: About how many texts a tile has on either side, and slots of the words that they may have in common.
TILE, COMMON = 256, 4096
#: Pairs of a tile that are aligned at once, if it has so many.
ALIGNED = 128
#: Comparisons that a key costs as much as: buckets of rare words go on by more special keys only where that is less work than to compare them.
PER_KEY = 64
#: How many of the rarest words a narrowed key holds at most.
DEPTH = 3
#: How many rare words before those of its key a text keeps, to tell where a pair has met already: pairs without a common word among these may meet again.
BEFORE = 16
#: Words of 64 bits in a text's bitmap.
BITS = 8
#: Bits of the filter of the ids whose words are fetched: beyond it more words are fetched and left out later.
FILTER = 1 << 26


def plan(threshold: float, recall: float, k: int, picks: int) -> int:
    """The number of sketches by which a pair at the threshold, its edits scattered at random, is found with probability ``recall``."""
    whole = threshold**k
    return math.ceil(math.log(1 - recall) / math.log(1 - (whole / (2 - whole)) ** picks))


class Hasher:
    """64-bit hashes of words, kept up to ``room``."""

    def __init__(self, room: int = 200_000) -> None:
        self.room, self.kept = room, {}

    def hashes(self, words: list[str]) -> np.ndarray:
        if len(self.kept) > self.room:
            self.kept = {}
        kept = self.kept
        for w in set(words).difference(kept):
            kept[w] = xxhash.xxh3_64_intdigest(w)
        return np.fromiter(map(kept.__getitem__, words), np.uint64, len(words))


def labels(values: np.ndarray, of: np.ndarray) -> np.ndarray:
    """How many equal values of the same text stand before each value."""
    order = np.lexsort((values, of))
    fresh = np.append(True, (values[order][1:] != values[order][:-1]) | (of[order][1:] != of[order][:-1]))
    out = np.empty(len(order), np.uint64)
    out[order] = (np.arange(len(order)) - np.maximum.accumulate(np.where(fresh, np.arange(len(order)), 0))).astype(np.uint64)
    return out


def sketch_block(texts: list[list[str]], hasher: Hasher, k: int, sketches: int, picks: int) -> tuple[np.ndarray, np.ndarray]:
    """Sketch values (texts, sketches) and which texts have any; a text of fewer than k words is one run."""
    sizes = np.array([len(t) for t in texts], np.int64)
    word = hasher.hashes([w for t in texts for w in t])
    runs = np.where(sizes > 0, np.maximum(sizes - k + 1, 1), 0)
    has = runs > 0
    out = np.zeros((len(texts), sketches), np.uint64)
    if not has.any():
        return out, has
    of = np.repeat(np.arange(len(texts)), runs)
    place = np.arange(len(of)) - np.repeat(np.cumsum(runs) - runs, runs)
    first = np.repeat(np.cumsum(sizes) - sizes, runs) + place
    gone = np.uint64(2**64 - 1)
    with np.errstate(over="ignore"):
        value = np.zeros(len(of), np.uint64)
        for i in range(k):
            inside = place + i < sizes[of]
            value = np.where(inside, mix(value + word[np.minimum(first + i, len(word) - 1)]), value)
        labelled = mix(value + labels(value, of) * np.uint64(0x9E3779B97F4A7C15))
        kept, dense = runs[has], np.cumsum(has)[of] - 1
        begins = np.cumsum(kept) - kept
        # an odd factor orders all 64-bit numbers anew
        factors = mix(np.arange(1, sketches + 1, dtype=np.uint64) * np.uint64(0xA0761D6478BD642F)) | np.uint64(1)
        for j in range(sketches):
            rank = labelled * factors[j]
            chosen = np.full((picks, len(begins)), len(of), np.int64)
            for pick in range(picks):
                least = np.minimum.reduceat(rank, begins)
                spots = np.flatnonzero((rank == np.repeat(least, kept)) & (rank != gone))[::-1]
                chosen[pick, dense[spots]] = spots  # of equal ranks the first
                rank[chosen[pick][chosen[pick] < len(of)]] = gone
            total = np.full(len(begins), j + 1, np.uint64)
            for spot in np.sort(chosen, axis=0):
                there = spot < len(of)
                total = np.where(there, mix(total + value[np.where(there, spot, 0)]), total)
            out[has, j] = total
    return out, has


def bitmaps(texts: list[np.ndarray]) -> np.ndarray:
    """(texts, BITS) 64-bit words: the bits that a text's words, equal ones told apart by their number, fall on.

    A word of one text without a partner in the other sets one bit at most, so near texts differ in few.
    """
    sizes = np.array([len(t) for t in texts], np.int64)
    of = np.repeat(np.arange(len(texts)), sizes)
    word = np.concatenate(texts).astype(np.uint64) if len(of) else np.zeros(0, np.uint64)
    with np.errstate(over="ignore"):
        bit = mix(word + labels(word, of) * np.uint64(0x9E3779B97F4A7C15)) % np.uint64(64 * BITS)
    out = np.zeros((len(texts), 64 * BITS), bool)
    out[of, bit.astype(np.int64)] = True
    return np.packbits(out, axis=1).view(np.int64)


def sketched(docs: DataFrame, id_col: str, text_col: str, k: int, sketches: int, picks: int, threshold: float) -> DataFrame:
    """(d, t1, t2, n, sketch, words, bits): the id, a 128-bit hash of the text, its number of words, the sketch values as longs, the word hashes and the bitmap.

    A text of up to SHORT words has no sketch; only texts that may be near to such a text have words.
    """
    upto = int(SHORT / threshold + 1e-9)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = Hasher()
        for batch in batches:
            counts, found, kept, bits = [], [], [], []
            for block in _blocks(batch.column(3)):
                texts = [t.lower().split() for t in block]
                values, has = sketch_block([t if len(t) > SHORT else [] for t in texts], hasher, k, sketches, picks)
                hashes = [hasher.hashes(t).astype("<u4") for t in texts]
                counts += [len(t) for t in texts]
                kept += [h.tobytes() if 0 < len(h) <= upto else None for h in hashes]
                found += [row.view(np.int64) if h else None for row, h in zip(values, has.tolist(), strict=True)]
                bits += list(bitmaps(hashes))
            yield pa.RecordBatch.from_arrays(
                [*batch.columns[:3], pa.array(counts, pa.int32()), pa.array(found, pa.list_(pa.int64())), pa.array(kept, pa.binary()), pa.array(bits, pa.list_(pa.int64()))],
                names=["d", "t1", "t2", "n", "sketch", "words", "bits"],
            )

    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    source = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("d"), F.xxhash64(text).alias("t1"), F.xxhash64(F.lit("second"), text).alias("t2"), text.alias("text"))
    return source.mapInArrow(run, "d long, t1 long, t2 long, n int, sketch array<long>, words binary, bits array<long>")


def as_words(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """(d, text) to (d, words) of the texts whose id is in ``ids``: 32-bit hashes of the words in one binary.

    A bitmap of the ids, of a fixed size, leaves most other texts out before anything is shuffled.
    """
    slot = F.pmod(F.xxhash64("d"), F.lit(FILTER))
    marked = ids.select(F.shiftright(slot, 5).alias("at"), F.expr(f"shiftleft(1L, CAST(pmod(xxhash64(d), {FILTER}L) AS INT) & 31)").alias("bit")).groupBy("at").agg(F.bit_or("bit").alias("bits")).toPandas()
    known = np.zeros(FILTER // 32, np.uint32)
    known[marked["at"].to_numpy(np.int64)] = marked["bits"].to_numpy(np.int64).astype(np.uint32)
    sent = docs.sparkSession.sparkContext.broadcast(known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = Hasher()
        for batch in batches:
            place = batch.column(2).to_numpy()
            hit = batch.filter(pa.array((sent.value[place >> 5] >> (place & 31).astype(np.uint32) & 1).astype(bool)))
            for at in range(0, hit.num_rows, 500):
                part = hit.slice(at, 500)
                words = [hasher.hashes((t.as_py() or "").lower().split()).astype("<u4").tobytes() for t in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(words, pa.binary())], names=["d", "words"])

    return docs.select("d", "text", slot.alias("slot")).mapInArrow(run, "d long, words binary").where("octet_length(words) > 0").join(ids, "d", "left_semi")


def rarity(texts: DataFrame) -> np.ndarray:
    """How many words of (d, words) fall in each slot of the word hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = np.zeros(SLOTS, np.int64)
        for batch in batches:
            for x in batch.column(0):
                count += np.bincount(np.frombuffer(x.as_py(), "<u4") % SLOTS, minlength=SLOTS)
        slot = np.flatnonzero(count)
        yield pa.RecordBatch.from_arrays([pa.array(slot.astype(np.int32)), pa.array(count[slot])], names=["slot", "n"])

    found = texts.select("words").mapInArrow(run, "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).toPandas()
    out = np.zeros(SLOTS, np.int64)
    out[found["slot"].to_numpy(np.int64)] = found["n"].to_numpy(np.int64)
    return out


def rarest(words: np.ndarray, count: np.ndarray, threshold: float, more: int = 0) -> np.ndarray:
    """Hashes of the rarest words of a text, rarest first, repeated words told apart.

    Near texts share all but threshold's rest of the longer one's words, so among so many of the rarest and one more both have a common
    word, and with each word more they have one more in common.
    """
    word = np.sort(words).astype(np.uint64)
    again = labels(word, np.zeros(len(word), np.int64))
    order = np.lexsort((again, word, count[(word % np.uint64(SLOTS)).astype(np.int64)]))[: int((1 - threshold) * len(word) + 1e-9) + 1 + more]
    with np.errstate(over="ignore"):
        return mix(word[order] + again[order] * np.uint64(0x9E3779B97F4A7C15))


def rare_words(texts: DataFrame, count: np.ndarray, threshold: float) -> DataFrame:
    """(d, words) to (d, p, rare): the rarest words of each text, of which the first p make keys."""
    sent = texts.sparkSession.sparkContext.broadcast(count)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                texts = [np.frombuffer(x.as_py(), "<u4") for x in part.column(1)]
                p = [int((1 - threshold) * len(t) + 1e-9) + 1 for t in texts]
                rare = [rarest(t, sent.value, threshold, DEPTH - 1).view(np.int64) for t in texts]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(p, pa.int32()), pa.array(rare, pa.list_(pa.int64()))], names=["d", "p", "rare"])

    return texts.select("d", "words").mapInArrow(run, "d long, p int, rare array<long>")


def rarer_keys(rows: DataFrame, rare: DataFrame, depth: int) -> DataFrame:
    """Rows (key, d, used) of keys of depth - 1 rare words go on by each rare word of their text after these; as all texts order words alike, no combination comes twice.

    ``ahead`` tells by how many keys each would go on.
    """
    after = "coalesce(array_position(rare, element_at(used, -1)), 0)"
    more = rows.join(rare, "d").select("key", "d", "used", F.expr(f"slice(rare, CAST({after} AS INT) + 1, greatest(p + {depth - 1} - CAST({after} AS INT), 0))").alias("next"))
    each = more.select("key", "d", "used", F.size("next").alias("n"), F.posexplode("next").alias("at", "w"))
    return each.select(F.xxhash64("key", "w").alias("key"), "d", F.expr("array_append(used, w)").alias("used"), (F.col("n") - F.col("at")).alias("ahead"))


def with_before(rows: DataFrame, rare: DataFrame) -> DataFrame:
    """Adds ``before``, the first words of the text that come before the last one used and aren't used, and what else ``rare`` tells of a text.

    Texts of one bucket that share one of them have met, or go on, at the key of that word: near texts have as many common words as a key may hold.
    """
    ahead = "array_except(slice(rare, 1, greatest(CAST(array_position(rare, element_at(used, -1)) AS INT) - 1, 0)), used)"
    # never null, which the engine would test in the join
    before = f"coalesce(slice({ahead}, 1, {BEFORE}), CAST(array() AS ARRAY<BIGINT>))"
    return rows.join(rare, "d").withColumn("before", F.expr(before)).drop("rare")


def with_earlier(rows: DataFrame, texts: DataFrame) -> DataFrame:
    """Adds ``before``, the keys of the text that stand before that of the row, and what else ``texts`` tells of it; two texts have their common keys in the same order."""
    before = "slice(keys, 1, greatest(CAST(array_position(keys, key) AS INT) - 1, 0))"
    return rows.join(texts, "d").withColumn("before", F.expr(before)).drop("keys")


def band_distances(pairs: list[tuple[np.ndarray, np.ndarray]], limits: np.ndarray, half: int) -> np.ndarray:
    """Edit distances of pairs inside a band of ``half`` cells on either side of the diagonal, all pairs row by row.

    Exact where it is at most ``half``; a pair of which every cell of a row exceeds its limit is given up with a larger value.
    """
    n = np.array([len(a) for a, _ in pairs])
    m = np.array([len(b) for _, b in pairs])
    width, big = 2 * half + 1, np.int32(1 << 28)
    rows, steps = len(pairs), int(n.max())
    left = np.zeros((rows, steps + 1), np.uint32)
    right = np.zeros((rows, int(m.max()) + steps + 2 * width), np.uint32)
    for i, (a, b) in enumerate(pairs):
        left[i, : len(a)] = a
        right[i, half : half + len(b)] = b
    shift = np.arange(width, dtype=np.int32)
    # cell (row i, shift w) stands for column i + w - half of the other text
    now = np.where(shift >= half, shift - half, big)[None, :].repeat(rows, 0).astype(np.int32)
    now[(shift - half)[None, :] > m[:, None]] = big
    out = np.where(n == 0, m, big).astype(np.int64)
    who = np.arange(rows)
    size, other, limit = n, m, limits
    for i in range(1, steps + 1):
        column = i + shift - half
        # character column - 1 of the other text lies at half + column - 1 of the padded one
        step = now + (right[:, i - 1 : i - 1 + width] != left[:, i - 1 : i])
        step[:, :-1] = np.minimum(step[:, :-1], now[:, 1:] + 1)
        outside = (column[None, :] < 0) | (column[None, :] > other[:, None])
        step[:, column == 0] = i
        step[outside] = big
        step = np.minimum(np.minimum.accumulate(step - shift, axis=1) + shift, big)
        step[outside] = big
        now = step.astype(np.int32)
        ends = np.flatnonzero(size == i)
        if len(ends):
            at = other[ends] - i + half
            fits = (at >= 0) & (at < width)
            out[who[ends[fits]]] = now[ends[fits], at[fits]]
        if i % 16 == 0 or len(ends):
            # pairs that have ended or can't come back below their limit are put aside
            live = np.flatnonzero((size > i) & (now.min(axis=1) <= limit))
            if not len(live):
                break
            if len(live) < 0.8 * len(who):
                now, left, right, who, size, other, limit = now[live], left[live], right[live], who[live], size[live], other[live], limit[live]
    return out


def near(pairs: list[tuple[np.ndarray, np.ndarray]], threshold: float) -> list[tuple[bool, int]]:
    """For each pair whether 1 - distance / longer length reaches the threshold, and the distance, -1 where it doesn't."""
    out: list[tuple[bool, int]] = [(False, -1)] * len(pairs)
    open_ = []
    for i, (a, b) in enumerate(pairs):
        longer = max(len(a), len(b))
        limit = int((1 - threshold) * longer + 1e-9)
        if abs(len(a) - len(b)) > limit:
            continue
        # equal ends need no alignment
        short = min(len(a), len(b))
        head = int(np.argmin(np.append(a[:short] == b[:short], False)))
        a, b, short = a[head:], b[head:], short - head
        tail = int(np.argmin(np.append(a[len(a) - short :][::-1] == b[len(b) - short :][::-1], False)))
        a, b = a[: len(a) - tail], b[: len(b) - tail]
        # every edit changes two counts of words at most
        least = int(np.abs(np.bincount(a % BINS, minlength=BINS) - np.bincount(b % BINS, minlength=BINS)).sum() + 1) // 2
        if least > limit:
            continue
        if not len(a) or not len(b):
            out[i] = (max(len(a), len(b)) <= limit, max(len(a), len(b)))
            continue
        open_.append((i, a, b, limit, least))
    half = 16
    while open_:
        # a band narrower than the bound can't hold the distance
        later = [x for x in open_ if x[4] > half]
        open_ = sorted((x for x in open_ if x[4] <= half), key=lambda x: len(x[1]))
        at = 0
        while at < len(open_):
            room = max(1, min(256, 40_000_000 // (len(open_[at][1]) + 8 * half + 1) // 8))
            part = open_[at : at + room]
            at += room
            limits = np.array([x[3] for x in part])
            found = band_distances([(x[1], x[2]) for x in part], limits, half)
            for (i, a, b, limit, least), distance in zip(part, found.tolist(), strict=True):
                if distance <= min(half, limit):
                    out[i] = (True, distance)
                elif half < limit:
                    later.append((i, a, b, limit, least))
        open_, half = later, 4 * half
    return out


def verify(pairs: DataFrame, threshold: float) -> DataFrame:
    """(a, b, left, right) to (a, b, near, distance)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for at in range(0, batch.num_rows, 2000):
                part = batch.slice(at, 2000)
                texts = [(np.frombuffer(x.as_py(), "<u4"), np.frombuffer(y.as_py(), "<u4")) for x, y in zip(part.column(2), part.column(3), strict=True)]
                found += near(texts, threshold)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([f for f, _ in found], pa.bool_()), pa.array([d for _, d in found], pa.int64())], names=["a", "b", "near", "distance"])

    return pairs.select("a", "b", "left", "right").mapInArrow(run, "a long, b long, near boolean, distance long")


def may_be_common(words: list[np.ndarray]) -> np.ndarray:
    """(texts, COMMON): the labelled words of each text by slots; the product of two rows is no less than what the texts have in common."""
    of = np.repeat(np.arange(len(words)), [len(t) for t in words])
    word = np.concatenate(words).astype(np.uint64)
    with np.errstate(over="ignore"):
        slot = mix(word + labels(word, of) * np.uint64(0x9E3779B97F4A7C15)) % np.uint64(COMMON)
    out = np.zeros((len(words), COMMON), np.float32)
    np.add.at(out, (of, slot.astype(np.int64)), np.float32(1))
    return out


def candidates(table: pa.Table, words: list[np.ndarray], threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Places of the pairs of a tile that meet at its key first, are of different components and pass the bounds, likely ones first.

    Texts outside the largest component are compared with it, and with those of a larger id.
    """
    d, c, n = (table[x].to_numpy() for x in ("d", "c", "n"))
    bits = table["bits"].combine_chunks().flatten().to_numpy().view(np.uint64).reshape(-1, BITS)
    at_top = c == table["top"].to_numpy()
    left, right = np.flatnonzero(table["is_left"].to_numpy()), np.flatnonzero(table["is_right"].to_numpy())
    x, y = left[:, None], right[None]
    a, b = np.nonzero((c[x] != c[y]) & (at_top[y] | (d[x] < d[y])) & (np.minimum(n[x], n[y]) >= np.maximum(n[x], n[y]) * threshold - 1e-9))
    a, b = left[a], right[b]
    longer = np.maximum(n[a], n[b])
    most = np.floor(longer * (1 - threshold) + 1e-9)
    few = np.ones(len(a), bool)
    for one, two in ((a, b), (b, a)):
        few &= np.bitwise_count(bits[one] & ~bits[two]).sum(axis=1, dtype=np.int64) <= most
    before = [frozenset(x) for x in table["before"].to_pylist()]
    few[few] = [before[i].isdisjoint(before[j]) for i, j in zip(a[few].tolist(), b[few].tolist(), strict=True)]
    a, b, longer, most = a[few], b[few], longer[few], most[few]
    if not len(a):
        return a, b
    used, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    common = may_be_common([words[i] for i in used])
    u, v = at[: len(a)], at[len(a) :]
    if len(used) ** 2 < 64 * len(a):
        shared = (common @ common.T)[u, v]
    else:
        shared = np.concatenate([np.einsum("ij,ij->i", common[u[k : k + 512]], common[v[k : k + 512]]) for k in range(0, len(a), 512)])
    least = longer - shared
    order = np.argsort(least, kind="stable")
    order = order[(least <= most)[order]]
    return a[order], b[order]


def connected(table: pa.Table, threshold: float) -> pa.Table:
    """(a, b, near, distance): near pairs of a tile by which its components are linked wherever any candidates of them are near.

    In each round every component has its likeliest pair aligned; pairs whose components have been linked meanwhile need no alignment.
    """
    words = [np.frombuffer(x, "<u4") for x in table["words"].to_pylist()]
    a, b = candidates(table, words, threshold)
    d = table["d"].to_numpy()
    _, root = np.unique(table["c"].to_numpy(), return_inverse=True)
    links: list[tuple[int, int, int]] = []
    while True:
        apart = root[a] != root[b]
        a, b = a[apart], b[apart]
        if not len(a):
            break
        # with so many more of the likeliest pairs at least, as few of them take as long
        likely = np.unique(np.concatenate([np.arange(min(len(a), ALIGNED)), *[np.unique(root[x], return_index=True)[1] for x in (a, b)]]))
        tried = near([(words[i], words[j]) for i, j in zip(a[likely].tolist(), b[likely].tolist(), strict=True)], threshold)
        hit = likely[[close for close, _ in tried]]
        links += zip(np.minimum(d[a[hit]], d[b[hit]]).tolist(), np.maximum(d[a[hit]], d[b[hit]]).tolist(), [far for close, far in tried if close], strict=True)
        if len(hit):
            node, label = components_of(root[a[hit]], root[b[hit]])
            onto = np.arange(root.max() + 1)
            onto[node] = label
            root = onto[root]
        a, b = np.delete(a, likely), np.delete(b, likely)
    one, two, far = zip(*links, strict=True) if links else ((), (), ())
    return pa.table({"a": pa.array(one, pa.int64()), "b": pa.array(two, pa.int64()), "near": pa.array([True] * len(one), pa.bool_()), "distance": pa.array(far, pa.int64())})


class Search:
    """The state of one search: scratch tables, verified pairs, and what a pair is verified with."""

    def __init__(self, scratch: Scratch, reps: DataFrame, threshold: float) -> None:
        self.scratch, self.threshold = scratch, threshold
        self.reps = reps
        self.bits = reps.select("d", "n", *[F.col("bits")[i].alias(f"x{i}") for i in range(BITS)])
        self.words: DataFrame | None = None
        self.known: DataFrame | None = None

    def may_be_near(self) -> Column:
        """Whether lengths n, m and bitmaps x0.., y0.. leave a pair a chance: each word without a partner costs an edit."""
        most = F.floor(F.greatest("n", "m") * (1 - self.threshold) + 1e-9)

        def alone(x: str, y: str) -> Column:
            return reduce(Column.__add__, [F.bit_count(F.col(f"{x}{i}").bitwiseAND(F.bitwise_not(f"{y}{i}"))) for i in range(BITS)])

        return (F.least("n", "m") >= F.greatest("n", "m") * self.threshold - 1e-9) & (alone("x", "y") <= most) & (alone("y", "x") <= most)

    def of_b(self) -> DataFrame:
        return self.bits.select(F.col("d").alias("b"), F.col("n").alias("m"), *[F.col(f"x{i}").alias(f"y{i}") for i in range(BITS)])

    def bounded(self, pairs: DataFrame) -> DataFrame:
        """The pairs (a, b) that pass the bounds."""
        both = pairs.distinct().join(self.bits.withColumnRenamed("d", "a"), "a").join(self.of_b(), "b")
        return both.where(self.may_be_near()).select("a", "b")

    def verify(self, pairs: DataFrame) -> None:
        """Align the pairs (a, b) that haven't been."""
        pairs = pairs.distinct()
        if self.known is not None:
            pairs = pairs.join(self.known.select("a", "b"), ["a", "b"], "left_anti")
        left, right = self.words.toDF("a", "left"), self.words.toDF("b", "right")
        self.learn(self.scratch.write(verify(pairs.join(left, "a").join(right, "b"), self.threshold)))

    def learn(self, found: DataFrame) -> None:
        self.known = found if self.known is None else self.known.unionByName(found)

    def links(self) -> DataFrame:
        return self.known.where("near").select("a", "b")

    def place(self) -> DataFrame:
        """(d, component, links) of the linked texts."""
        linked = self.links()
        degree = linked.select(F.explode(F.array("a", "b")).alias("node")).groupBy("node").agg(F.count("*").alias("links"))
        return self.scratch.write(components(self.scratch, linked).join(degree, "node").withColumnRenamed("node", "d"))

    def mixed(self, rows: DataFrame, place: DataFrame) -> DataFrame:
        """The rows of buckets whose texts are in several components: with the component c and the links of each text, the largest component
        ``top`` of its bucket, its ``size`` and how many are ``outside`` that component, and ``work``, the comparisons of these with all; where rows tell
        how many keys lie ahead, also their number ``more``."""
        placed = rows.join(place, "d", "left").withColumn("c", F.coalesce("component", "d")).withColumn("links", F.coalesce("links", F.lit(0))).drop("component")
        ahead = F.sum("ahead" if "ahead" in rows.columns else F.lit(0)).alias("more")
        parts = placed.groupBy("key", "c").agg(F.count("*").alias("n"), ahead).groupBy("key").agg(F.max(F.struct("n", "c")).alias("most"), F.sum("n").alias("size"), F.sum("more").alias("more"))
        outside = F.col("size") - F.col("most.n")
        several = parts.where("size > most.n").select("key", F.col("most.c").alias("top"), "size", outside.alias("outside"), (outside * F.col("size")).alias("work"), "more")
        return self.scratch.write(placed.join(several, "key"))

    def within(self, rows: DataFrame, rare: DataFrame | None = None) -> DataFrame:
        """Pairs (a, b) of different components of a bucket that pass the bounds; only texts outside the largest component are compared with others.

        With ``rare``, the rare words of each text, pairs that share one before those of the key are left to the key of that word.
        """
        before = [] if rare is None else ["before"]
        if rare is None:
            with_bits = rows.select("key", "d", "c", "top").join(self.bits, "d")
        else:
            with_bits = with_before(rows.select("key", "d", "c", "top", "used"), self.bits.join(rare.select("d", "rare"), "d")).drop("used")
        one = with_bits.where("c <> top").drop("top").withColumnRenamed("d", "a")
        two = with_bits.select(
            "key", F.col("d").alias("b"), F.col("c").alias("c2"), "top", F.col("n").alias("m"), *[F.col(f"x{i}").alias(f"y{i}") for i in range(BITS)], *[F.col(x).alias("before2") for x in before]
        )
        met = one.join(two, "key").where("c <> c2 AND (c2 = top OR a < b)").where(self.may_be_near())
        met = met.where("NOT arrays_overlap(before, before2)") if before else met
        return self.scratch.write(met.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())

    def across(self, rows: DataFrame, keys: DataFrame, marked: Callable[[DataFrame, DataFrame], DataFrame]) -> None:
        """Links of rows of ``mixed`` found over tiles of their buckets, so that no pair is shuffled; each text first in the smallest of its buckets, then all that is left.

        ``marked`` joins the rows with their texts, which hold ``keys``, and adds ``before``, what leaves a pair that shares it to another key.
        """
        if rows.isEmpty():
            return
        texts = self.words.join(rows.select("d").distinct(), "d", "left_semi").join(self.reps.select("d", "n", "bits"), "d").join(keys, "d")
        texts = self.scratch.write(texts)
        smallest = rows.groupBy("d").agg(F.min_by("key", F.struct("size", "key")).alias("key"))
        self.tiled(marked(rows.join(smallest, ["d", "key"], "left_semi"), texts).withColumn("before", F.expr("CAST(array() AS ARRAY<BIGINT>)")))
        rest = self.mixed(rows.drop("c", "links", "top", "size", "outside", "work", "more"), self.place())
        self.tiled(marked(rest, texts))

    def tiled(self, rows: DataFrame) -> None:
        spread = rows.withColumn("i", F.ceil(F.col("outside") / TILE)).withColumn("j", F.ceil(F.col("size") / TILE))
        # a bucket of one tile needs each text once, otherwise texts stand for its left and its right side in all tiles of their row or column
        side = """CASE WHEN i = 1 AND j = 1 THEN array(struct(0L AS i, 0L AS j, c <> top AS is_left, true AS is_right)) ELSE concat(
            if(c <> top, transform(sequence(0L, j - 1), x -> struct(pmod(xxhash64(d), i) AS i, x AS j, true AS is_left, false AS is_right)), array()),
            transform(sequence(0L, i - 1), x -> struct(x AS i, pmod(xxhash64(d), j) AS j, false AS is_left, true AS is_right))) END"""
        spread = spread.select("key", "d", "c", "top", "n", "bits", "words", "before", F.explode(F.expr(side)).alias("side")).select("*", "side.*").drop("side")
        threshold = self.threshold
        self.learn(self.scratch.write(spread.groupBy("key", "i", "j").applyInArrow(lambda tile: connected(tile, threshold), "a long, b long, near boolean, distance long")))


def near_duplicates(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 5, sketches: int | None = None, picks: int = 2, threshold: float = 0.8,
    recall: float = 0.92,
) -> DataFrame:
    """The near-duplicate class of every document.

    Returns one row per distinct non-null id: (id_col, same_as, cluster_id, kept). same_as is the smallest id with the very same text,
    cluster_id the smallest id reachable by links of equal or near texts, kept whether the row is that one. Null and empty
    texts are equal to each other and near nothing else; null ids can't be named and are left out; rows that repeat an id are one
    document, near to what any of its texts is near to. An empty table gives an empty one. Links of texts of up to SHORT words are all found,
    those of longer texts at the threshold with probability ``recall``, closer ones with more; ``sketches`` is set by it if not given.
    """
    scratch = Scratch(docs.sparkSession, "near-duplicates")
    all_ = scratch.write(sketched(docs, id_col, text_col, k, sketches or plan(threshold, recall, k, picks), picks, threshold))
    ids = scratch.write(all_.select("d", "t1", "t2"))
    same = all_.groupBy("t1", "t2").agg(F.min("d").alias("d"), *[F.first(c).alias(c) for c in ("n", "sketch", "words", "bits")])
    reps = scratch.write(same.where("n > 0").select("d", "n", "sketch", "words", "bits"))
    scratch.drop(all_)
    scratch.release()
    search = Search(scratch, reps, threshold)

    short = reps.where("words is not null").select("d", "words")
    short_rare = rare_words(short, rarity(short), threshold)
    by_word = short_rare.select(F.explode(F.expr("slice(rare, 1, p)")).alias("key"), "d")
    keys = reps.select(F.explode("sketch").alias("key"), "d").unionByName(by_word)
    # the smallest id of each bucket leads first; lone rows are left out
    lead = keys.groupBy("key").agg(F.min("d").alias("a"), F.max("d").alias("last")).where("a <> last").select("key", "a")
    rest = scratch.write(keys.join(lead.hint("merge"), "key"))
    texts = docs.select(F.col(id_col).cast("long").alias("d"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    search.words = scratch.write(as_words(texts, scratch.write(rest.select("d").distinct())))
    # a text first meets the one that leads most of its buckets
    most = rest.where("d <> a").groupBy("d", "a").agg(F.count("*").alias("n")).groupBy("d").agg(F.max(F.struct("n", -F.col("a"))).alias("l"))
    search.verify(search.bounded(most.select((-F.col("l.col2")).alias("a"), F.col("d").alias("b"))))
    scratch.release()

    # then, where a bucket's texts are in several components, the text with most links
    rest = search.mixed(rest.select("key", "d"), search.place())
    hub = rest.groupBy("key").agg(F.max(F.struct("links", -F.col("d"), "c")).alias("h")).select("key", (-F.col("h.col2")).alias("lead"), F.col("h.c").alias("led"))
    met = rest.join(hub, "key").where("c <> led")
    search.verify(search.bounded(met.select(F.least("lead", "d").alias("a"), F.greatest("lead", "d").alias("b"))))

    place = search.place()
    rest = search.mixed(rest.select("key", "d"), place)
    pairs = search.within(rest.where(F.col("work") <= WORK))
    in_tiles = F.col("work") <= max(WORK, RARE_WORK)
    own = reps.select("d", "sketch").join(short_rare, "d", "left")
    own = own.select("d", F.expr("concat(coalesce(sketch, array()), coalesce(slice(rare, 1, p), array()))").alias("keys"))
    search.across(rest.where((F.col("work") > WORK) & in_tiles), own, with_earlier)
    crowded = rest.where((F.col("work") > WORK) & ~in_tiles).select("d").distinct()
    words = scratch.write(search.words.join(crowded, "d", "left_semi"))
    if not words.isEmpty():
        place = search.place()
        rare = scratch.write(rare_words(words, rarity(words), threshold))
        narrow = rare.select("d", "p", F.posexplode(F.expr("slice(rare, 1, p)")).alias("at", "key")).select("key", "d", F.array("key").alias("used"), (F.col("p") - F.col("at")).alias("ahead"))
        for depth in range(1, DEPTH + 1):
            narrow = search.mixed(narrow, place)
            # what shares so many rare words is compared in full, as is what would make more work as keys
            light = (F.col("work") <= RARE_WORK) | (F.col("work") <= PER_KEY * F.col("more"))
            full = narrow if depth == DEPTH else narrow.where(light)
            pairs = pairs.unionByName(search.within(full.where(F.col("work") <= WORK), rare))
            search.across(full.where(F.col("work") > WORK), rare.select("d", "rare"), with_before)
            narrow = narrow.where(~light).select("key", "d", "used")
            if depth == DEPTH or narrow.isEmpty():
                break
            narrow = rarer_keys(narrow, rare, depth + 1)
    search.verify(pairs)
    scratch.release()

    first = ids.groupBy("t1", "t2").agg(F.min("d").alias("rep"))
    same_text = ids.join(first, ["t1", "t2"]).select("d", "rep").distinct()
    edges = same_text.where("d <> rep").select(F.col("rep").alias("a"), F.col("d").alias("b")).unionByName(search.links())
    label = components(scratch, edges)
    each = same_text.groupBy("d").agg(F.min("rep").alias("same_as"))
    cluster = F.coalesce("component", "d")
    return scratch.finish(each.join(label, each.d == label.node, "left").select(F.col("d").alias(id_col), "same_as", cluster.alias("cluster_id"), (cluster == F.col("d")).alias("kept")))


def _blocks(column) -> Iterator[list[str]]:
    block: list[str] = []
    held = 0
    for text in column:
        block.append(text.as_py() or "")
        held += len(block[-1])
        if held >= BLOCK_CHARS:
            yield block
            block, held = [], 0
    if block:
        yield block
