"""What the training-data operators share: scratch tables in the cluster's shared folder, and connected components."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``.

    Where it is unset, a local master gets a temporary folder and a cluster gets a folder below the warehouse.
    """
    set_by_cluster = spark.conf.get("spark.checkpoint.dir", "") or spark.sparkContext.getConf().get("spark.checkpoint.dir", "")
    if set_by_cluster:
        return set_by_cluster.rstrip("/")
    if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
        known = getattr(shared_dir, "local", None)
        if known is None:
            known = shared_dir.local = "file://" + tempfile.mkdtemp(prefix="pairsample-")
        return known
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch"


_KEPT: dict = {}


def kept_by_worker(key: tuple | None, make: Callable[[], Any] = lambda: None) -> Any:
    """The one object that a worker process keeps between tasks, made anew where another is wanted; None keeps none.

    Workers serve all operators of a job one after another, so a cache of one must not stay beside that of the next.
    """
    if key not in _KEPT:
        if _KEPT:
            _KEPT.clear()
            gc.collect()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (AttributeError, OSError):  # another C library: freed memory stays with the process
                pass
        if key is None:
            return None
        _KEPT[key] = make()
    return _KEPT[key]


class Scratch:
    """Tables that cut lineage: each is written once to the shared folder and read back with the same schema."""

    def __init__(self, spark: SparkSession, what: str) -> None:
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
        self.made = 0

    def write(self, df: DataFrame) -> DataFrame:
        self.made += 1
        path = f"{self.root}/{self.made}"
        df.write.parquet(path)
        kept = self.spark.read.schema(df.schema).parquet(path)
        kept._scratch_path = path
        return kept

    def finish(self, df: DataFrame) -> DataFrame:
        """The result written as the last table, all others deleted."""
        done = self.write(df)
        for k in range(1, self.made):
            self._delete(f"{self.root}/{k}")
        return done

    def drop(self, df: DataFrame) -> None:
        """Delete a table of this object that no later step reads."""
        self._delete(df._scratch_path)

    def release(self) -> None:
        """Let Spark remove the shuffle files of finished steps, which otherwise stay until the driver happens to collect its garbage."""
        gc.collect()
        self.spark._jvm.System.gc()

    def _delete(self, where: str) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(where)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


#: Edges up to which components are found by the driver.
HELD_EDGES = 300_000


def components_of(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of an edge list in order, and the smallest node of each one's component."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    x, y = at[: len(u)], at[len(u) :]
    label = np.arange(len(nodes))
    while True:
        # the root of either end hangs on the smaller label of the two, then all nodes on the roots of their labels
        least = np.minimum(label[x], label[y])
        np.minimum.at(label, label[x], least)
        np.minimum.at(label, label[y], least)
        while (label[label] != label).any():
            label = label[label]
        if (label[x] == label[y]).all():
            return nodes, nodes[label]


def components(scratch: Scratch, edges: DataFrame, a: str = "a", b: str = "b", held_edges: int = HELD_EDGES) -> DataFrame:
    """Connected components of an edge list: one row (node, component) per node, component being its smallest node.

    Up to ``held_edges`` distinct edges, which are counted, go to the driver, as that takes no stages. More stay distributed.
    Alternates two star contractions until nothing changes. A hub never meets its neighbours in one
    place: minima are map-side combined, and the joins that follow can be split where a key is hot.
    Nulls and self loops are ignored; an empty edge list gives an empty table.
    """
    now = scratch.write(
        edges.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v"))
        .where("u is not null and v is not null and u <> v")
        .select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        .distinct()
    )

    def state(table: DataFrame) -> tuple:
        return tuple(table.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))"), F.expr("bit_xor(xxhash64(v, u, 1))")).first())

    seen = state(now)
    if seen[0] <= held_edges:
        held = now.toArrow()
        scratch.drop(now)
        node, component = components_of(held["u"].to_numpy(), held["v"].to_numpy())
        return scratch.write(scratch.spark.createDataFrame(pa.table({"node": node.astype(np.int64), "component": component.astype(np.int64)}), "node long, component long"))
    while True:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        # every larger neighbour of u, and u itself, hangs on the smallest node around u
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        own = least.where("m < u").select("u", F.col("m").alias("v"))
        star = large.unionByName(own).where("u <> v").distinct()
        down = star.groupBy("u").agg(F.min("v").alias("m"))
        # among the smaller neighbours of u, all hang on the smallest
        small = star.join(down, "u").where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        nxt = scratch.write(small.unionByName(down.select("u", F.col("m").alias("v"))).distinct())
        scratch.drop(now)
        now, before, seen = nxt, seen, state(nxt)
        if seen == before:
            break
    roots = now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
