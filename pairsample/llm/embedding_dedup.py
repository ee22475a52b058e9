"""Near-duplicate vectors by Euclidean p-stable hashing, with exact cosines.

Vectors are scaled to length 1. Each of several tables quantises ``depth`` Gaussian projections in steps of ``step``; equal cells
make a bucket. Both numbers follow the size of the input: the depth so that a vector meets about one unrelated vector per table, the number of
tables so that a pair at the threshold meets in at least one of them with probability ``recall``.

Dense groups are not expanded. In each bucket every vector is compared with the smallest id, the leader; those within a
small angle of a leader form its ball. Two vectors of one ball are linked by the triangle inequality. Balls that meet in a
bucket are compared by their leaders: either all their vectors are linked, or none, or, where the bounds don't decide, the cosines of
their vectors are taken one by one in double precision.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairsample.llm.common import Scratch, components

STEP = 3.0
#: The ball's share of the threshold's angle.
BALL = 0.125
SIGNS = 128
#: More than an angle from a cosine of doubles can be off by; pairs of balls closer to a bound are decided by their vectors.
MARGIN = 1e-7


def meets(distance: float, step: float) -> float:
    """Probability that two vectors at a distance fall into the same cell of one projection."""
    x = step / distance
    return math.erf(x / math.sqrt(2)) - 2 / (math.sqrt(2 * math.pi) * x) * (1 - math.exp(-x * x / 2))


def plan(rows: int, threshold: float, recall: float) -> tuple[int, int]:
    """Depth and number of tables for so many rows."""
    near, far = meets(math.sqrt(2 - 2 * threshold), STEP), meets(math.sqrt(2), STEP)
    depth = max(4, math.ceil(math.log(max(rows, 2)) / -math.log(far)))
    return depth, math.ceil(math.log(1 - recall) / math.log(1 - near**depth))


def hashed(vectors: DataFrame, id_col: str, vector_col: str, depth: int, tables: int, seed: int) -> DataFrame:
    """(v, unit, s1, s2, keys): unit vectors as binary doubles, 128 signs of random projections, one bucket key per table.

    Vectors that are null, zero, or hold a null or a number that isn't finite have no unit vector and no keys.
    """
    # drawn per dimension, so that vectors of any length are hashed alike in every task
    mixers = np.random.default_rng(seed).integers(1, 2**63, depth, dtype=np.uint64) | np.uint64(1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        drawn: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        for batch in batches:
            lists = batch.column(1).to_pylist()
            units: list[bytes | None] = [None] * len(lists)
            keys: list[np.ndarray | None] = [None] * len(lists)
            signs: list[tuple[int | None, int | None]] = [(None, None)] * len(lists)
            by_size: dict[int, list[int]] = {}
            for i, x in enumerate(lists):
                if x is not None and len(x) and None not in x:
                    by_size.setdefault(len(x), []).append(i)
            for size, rows in by_size.items():
                if size not in drawn:
                    rng = np.random.default_rng([seed, size])
                    drawn[size] = rng.standard_normal((size, tables * depth)), rng.uniform(0, STEP, tables * depth), rng.standard_normal((size, SIGNS))
                lines, offsets, planes = drawn[size]
                x = np.array([lists[i] for i in rows], np.float64)
                with np.errstate(all="ignore"):
                    x = x / np.abs(x).max(axis=1, keepdims=True)
                    x = x / np.sqrt((x * x).sum(axis=1, keepdims=True))
                good = np.isfinite(x).all(axis=1)
                rows, x = [i for i, g in zip(rows, good.tolist(), strict=True) if g], x[good]
                if not rows:
                    continue
                cells = np.floor((x @ lines + offsets) / STEP).astype(np.int64).astype(np.uint64).reshape(len(x), tables, depth)
                with np.errstate(over="ignore"):
                    total = np.full((len(x), tables), size, np.uint64) + np.arange(tables, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
                    for d in range(depth):
                        total = (total ^ cells[:, :, d]) * mixers[d]
                        total ^= total >> np.uint64(29)
                bits = np.packbits(x @ planes > 0, axis=1).view(np.int64)
                for k, i in enumerate(rows):
                    units[i], keys[i], signs[i] = x[k].tobytes(), total[k].view(np.int64), (int(bits[k, 0]), int(bits[k, 1]))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(units, pa.binary()), pa.array([s[0] for s in signs], pa.int64()), pa.array([s[1] for s in signs], pa.int64()), pa.array(keys, pa.list_(pa.int64()))],
                names=["v", "unit", "s1", "s2", "keys"],
            )

    source = vectors.select(F.col(id_col).cast("long").alias("v"), F.col(vector_col).cast("array<double>").alias("x"))
    return source.mapInArrow(run, "v long, unit binary, s1 long, s2 long, keys array<long>")


def cosines(pairs: DataFrame, names: str) -> DataFrame:
    """Adds ``cos`` to rows that hold unit vectors ``left`` and ``right``; of the other columns those of ``names`` stay."""
    kept = [c.split()[0] for c in names.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cos = []
            for x, y in zip(batch.column(len(kept)), batch.column(len(kept) + 1), strict=True):
                a, b = np.frombuffer(x.as_py()), np.frombuffer(y.as_py())
                cos.append(float((a * b).sum()) if len(a) == len(b) else -1.0)
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(kept)], pa.array(cos, pa.float64())], names=[*kept, "cos"])

    return pairs.select(*kept, "left", "right").mapInArrow(run, f"{names}, cos double")


def _angle(cos: Column) -> Column:
    return F.when(cos.isNotNull(), F.acos(F.least(F.greatest(cos, F.lit(-1.0)), F.lit(1.0))))


def linked_vectors(
    vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", threshold: float = 0.9, recall: float = 0.97, seed: int = 11,
) -> DataFrame:
    """Links of cosine at least ``threshold`` between all vectors, as one row per vector.

    Returns (id_col, n_links, component_id, kept). Every link reported is one by its cosine in double precision; a pair just at the threshold
    is found with probability ``recall``, closer ones with more. Vectors that are null, zero, of another length, or hold a
    null or a number that isn't finite link with nothing. Rows that repeat an id are one vector (of different vectors the first in byte order); null ids
    are left out. An empty table gives an empty one.
    """
    spark = vectors.sparkSession
    scratch = Scratch(spark, "vectors")
    rows = vectors.where(F.col(id_col).isNotNull())
    depth, tables = plan(rows.count(), threshold, recall)
    raw = hashed(rows, id_col, vector_col, depth, tables, seed)
    all_ = scratch.write(raw.groupBy("v").agg(*[F.min_by(c, F.coalesce("unit", F.lit(b""))).alias(c) for c in ("unit", "s1", "s2", "keys")]))
    units = all_.where("unit is not null").select("v", "unit")
    theta = math.acos(threshold)
    ball = BALL * theta

    # every vector and the leader of each of its buckets
    keys = all_.where("keys is not null").select("v", F.posexplode("keys").alias("at", "key"))
    lead = keys.groupBy("at", "key").agg(F.min("v").alias("lead"), F.max("v").alias("last")).where("lead <> last")
    near = keys.join(lead.select("at", "key", "lead"), ["at", "key"]).where("v <> lead").select("v", "lead").distinct()
    signs = all_.select(F.col("v").alias("w"), F.col("s1").alias("t1"), F.col("s2").alias("t2"))

    def alike(angle: float) -> Column:
        """Signs differ in no more places than vectors within the angle may, by five deviations."""
        p = angle / math.pi
        most = math.floor(SIGNS * p + 5 * math.sqrt(SIGNS * p * (1 - p)))
        return F.bit_count(F.col("s1").bitwiseXOR(F.col("t1"))) + F.bit_count(F.col("s2").bitwiseXOR(F.col("t2"))) <= most

    screened = near.join(all_.select("v", "s1", "s2"), "v").join(signs.withColumnRenamed("w", "lead"), "lead").where(alike(ball)).select("v", "lead")
    with_units = screened.join(units.withColumnRenamed("unit", "left"), "v").join(units.select(F.col("v").alias("lead"), F.col("unit").alias("right")), "lead")
    close = scratch.write(cosines(with_units, "v long, lead long").where(F.col("cos") >= math.cos(ball)))
    # a leader that follows no other keeps its ball; who follows one that has itself a leader stands alone unless another leader takes it
    free = close.select(F.col("lead").alias("w")).distinct().join(close.select(F.col("v").alias("w")).distinct(), "w", "left_anti").withColumnRenamed("w", "lead")
    taken = close.join(free, "lead").groupBy("v").agg(F.min(F.struct("lead", "cos")).alias("of"))
    placed = scratch.write(
        all_.where("unit is not null").select("v", "s1", "s2").join(taken, "v", "left")
        .select("v", "s1", "s2", F.coalesce("of.lead", "v").alias("ball"), F.coalesce(_angle(F.col("of.cos")), F.lit(0.0)).alias("off"))
    )
    balls = scratch.write(placed.groupBy("ball").agg(F.count("*").alias("size"), F.max("off").alias("radius")))

    # balls that meet in a bucket, by their leaders
    of = placed.select("v", "ball")
    rooms = keys.join(of, "v").select("at", "key", "ball").distinct()
    sign = placed.where("v = ball").select("ball", "s1", "s2")
    rooms = rooms.join(rooms.groupBy("at", "key").count().where("count > 1").select("at", "key"), ["at", "key"]).join(sign, "ball")
    other = rooms.select("at", "key", F.col("ball").alias("other"), F.col("s1").alias("t1"), F.col("s2").alias("t2"))
    met = rooms.join(other, ["at", "key"]).where("ball < other").where(alike(theta + 2 * ball)).select("ball", "other").distinct()
    center = units.select(F.col("v").alias("ball"), F.col("unit").alias("left"))
    facing = met.join(center, "ball").join(center.select(F.col("ball").alias("other"), F.col("left").alias("right")), "other")
    sized = (
        cosines(facing, "ball long, other long")
        .join(balls, "ball")
        .join(balls.select(F.col("ball").alias("other"), F.col("size").alias("other_size"), F.col("radius").alias("other_radius")), "other")
    )
    slack = F.col("radius") + F.col("other_radius")
    both = scratch.write(
        sized.withColumn("angle", _angle(F.col("cos"))).where((F.col("angle") - slack <= theta + MARGIN) | (F.col("cos") >= threshold))
        .withColumn("whole", F.when(slack == 0, F.col("cos") >= threshold).otherwise(F.col("angle") + slack <= theta - MARGIN))
    )
    single = both.where("whole or size + other_size > 2")
    halfway = single.where("not whole").select("ball", "other")
    members = placed.select("v", "ball").join(units, "v")
    one = halfway.join(members.select("ball", F.col("v").alias("a"), F.col("unit").alias("left")), "ball")
    two = one.join(members.select(F.col("ball").alias("other"), F.col("v").alias("b"), F.col("unit").alias("right")), "other")
    pairs = scratch.write(cosines(two, "a long, b long").where(F.col("cos") >= threshold).select("a", "b"))

    whole = both.where("whole")
    by_ball = whole.select("ball", F.col("other_size").alias("n")).unionByName(whole.select(F.col("other").alias("ball"), F.col("size").alias("n"))).groupBy("ball").agg(F.sum("n").alias("around"))
    by_vector = pairs.select(F.col("a").alias("v")).unionByName(pairs.select(F.col("b").alias("v"))).groupBy("v").agg(F.count("*").alias("one_by_one"))
    edges = placed.where("v <> ball").select(F.col("ball").alias("a"), F.col("v").alias("b")).unionByName(whole.select(F.col("ball").alias("a"), F.col("other").alias("b"))).unionByName(pairs)
    label = components(scratch, edges)
    counted = (
        all_.select("v").join(of, "v", "left").join(balls.select("ball", "size"), "ball", "left").join(by_ball, "ball", "left").join(by_vector, "v", "left")
        .join(label.withColumnRenamed("node", "v"), "v", "left")
    )
    links = F.coalesce(F.col("size") - 1, F.lit(0)) + F.coalesce("around", F.lit(0)) + F.coalesce("one_by_one", F.lit(0))
    component = F.coalesce("component", "v")
    return counted.select(F.col("v").alias(id_col), links.cast("long").alias("n_links"), component.alias("component_id"), (component == F.col("v")).alias("kept"))
