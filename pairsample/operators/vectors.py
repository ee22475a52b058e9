"""Pairs of vectors that share a band of signs, compared over tiles of blocks, so that no pair is shuffled.

Vectors are dealt over blocks by a hash of their id; a tile is a pair of blocks. Each tile gets the vectors and sign codes of both, and finds the pairs
that may reach the cosine by a matrix product of single precision with a margin. What shares a band among these gets its cosine in double precision, summed in
the order of the components. A pair is so met in one tile, however many bands it shares, and a block is the same work whatever its vectors' signs are.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.operators.tiles import tile_at, tile_number

#: Vectors of a block about at most, and how many blocks few vectors are dealt over at most, of at least so many.
BLOCK, BLOCKS, LEAST = 131_072, 8, 64
#: Rows and columns of a matrix product, and pairs whose cosines are taken at once.
ROWS, COLUMNS, ROOM = 1024, 8192, 200_000
#: More than a product of single precision can be off by, for vectors of up to a thousand components.
MARGIN = 1e-4


def summed(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Inner products of rows in double precision, one component after another."""
    total = np.zeros(len(x))
    for d in range(x.shape[1]):
        total += x[:, d].astype(np.float64) * y[:, d]
    return total


def codes_of(x: np.ndarray, normals: np.ndarray) -> np.ndarray:
    """(vectors, bands): the signs of each band as one number; a dot that isn't a number counts as positive, as in the engine's order."""
    bands, bits, dim = normals.shape
    flat = normals.reshape(bands * bits, dim)
    dots = np.zeros((len(x), bands * bits))
    with np.errstate(invalid="ignore", over="ignore"):
        for d in range(dim):
            dots += x[:, d, None].astype(np.float64) * flat[:, d]
        signs = ~(dots <= 0)
    out = np.zeros((len(x), bands), np.uint64)
    for b in range(bits):
        out = out << np.uint64(1) | signs.reshape(len(x), bands, bits)[:, :, b]
    return out.astype(np.uint8 if bits <= 8 else np.uint16 if bits <= 16 else np.uint64)


def near_pairs(x: np.ndarray, y: np.ndarray, codes_x: np.ndarray, codes_y: np.ndarray, at_least: float, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Places and cosines of the pairs of two blocks that share a code of a band; within one block each pair once."""
    with np.errstate(all="ignore"):
        norm_x, norm_y = summed(x, x), summed(y, y)
        # what has no usable length is no number here and goes on to the exact test
        unit_x, unit_y = ((v / np.where(n > 0, np.sqrt(n), np.nan)[:, None]).astype(np.float32) for v, n in ((x, norm_x), (y, norm_y)))
        for r in range(0, len(x), ROWS):
            for c in range(r // COLUMNS * COLUMNS if same else 0, len(y), COLUMNS):
                i, j = np.nonzero(~(unit_x[r : r + ROWS] @ unit_y[c : c + COLUMNS].T < at_least - MARGIN))
                i, j = i + r, j + c
                if same:
                    i, j = i[i < j], j[i < j]
                for at in range(0, len(i), ROOM):
                    a, b = i[at : at + ROOM], j[at : at + ROOM]
                    met = (codes_x[a] == codes_y[b]).any(axis=1)
                    a, b = a[met], b[met]
                    cos = summed(x[a], y[b]) / np.sqrt(norm_x[a] * norm_y[b])
                    near = ~(cos < at_least)
                    if near.any():
                        yield a[near], b[near], cos[near]


def band_pairs(rows: DataFrame, normals: np.ndarray, at_least: float) -> DataFrame:
    """(v, x), x of floats or doubles without nulls, to (i, j, cos), i < j, of the pairs that share the signs of a band and reach the cosine.

    A cosine that isn't a number (of lengths that are zero or not finite) is above all numbers, as in both engines. Of rows that repeat an id each is compared by
    its own signs.
    """
    n = rows.count()
    blocks = max(-(-n // BLOCK), min(BLOCKS, -(-n // LEAST)), 1)
    kind, number = rows.schema["v"].dataType.simpleString(), np.dtype("<f4" if rows.schema["x"].dataType.simpleString() == "array<float>" else "<f8")
    bands, _, dim = normals.shape

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            x = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(number).reshape(batch.num_rows, dim)
            codes = codes_of(x, normals)
            of = batch.column(2).to_numpy(zero_copy_only=False)
            for own in np.unique(of).tolist():
                at = np.flatnonzero(of == own)
                ids = batch.column(0).take(pa.array(at))
                packed, signs = x[at].tobytes(), codes[at].tobytes()
                lists = pa.ListArray.from_arrays(pa.array([0, len(at)], pa.int32()), ids)
                for other in range(blocks):
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([tile_number(min(own, other), max(own, other))], pa.int32()), pa.array([own], pa.int32()), lists, pa.array([packed], pa.binary()), pa.array([signs], pa.binary())],
                        names=["tile", "block", "ids", "vectors", "codes"],
                    )

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, dict[int, list]] = {}
        for batch in batches:
            for k in range(batch.num_rows):
                tile, own = batch.column(0)[k].as_py(), batch.column(1)[k].as_py()
                held.setdefault(tile, {}).setdefault(own, []).append((batch.column(2)[k].values, batch.column(3)[k].as_py(), batch.column(4)[k].as_py()))
        for tile in list(held):
            parts = held.pop(tile)
            whole = {}
            for own in list(parts):
                ids, packed, signs = zip(*parts.pop(own), strict=True)
                signs = np.frombuffer(b"".join(signs), np.uint8)
                ids = pa.concat_arrays(ids)
                whole[own] = ids, np.frombuffer(b"".join(packed), number).reshape(len(ids), dim), signs.view(f"<u{len(signs) // (len(ids) * bands)}").reshape(len(ids), bands)
            x, y = tile_at(tile)
            if x not in whole or y not in whole:
                continue
            (left, vx, cx), (right, vy, cy) = whole[x], whole[y]
            for i, j, cos in near_pairs(vx, vy, cx, cy, at_least, x == y):
                yield pa.RecordBatch.from_arrays([left.take(pa.array(i)), right.take(pa.array(j)), pa.array(cos)], names=["v", "w", "cos"])

    placed = rows.select("v", "x", F.pmod(F.xxhash64("v"), F.lit(blocks)).cast("int").alias("block"))
    dealt = placed.mapInArrow(deal, f"tile int, block int, ids array<{kind}>, vectors binary, codes binary")
    met = dealt.repartitionById(blocks * (blocks + 1) // 2, F.col("tile")).mapInArrow(compare, f"v {kind}, w {kind}, cos double")
    return met.where("v <> w").select(F.least("v", "w").alias("i"), F.greatest("v", "w").alias("j"), "cos")
