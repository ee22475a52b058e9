"""Pairs of texts that share many keys are made once, and components don't depend on where they are found."""

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from pairsample.llm import order_minhash
from pairsample.llm.common import Scratch, components, components_of


def test_a_pair_meets_at_one_key_of_each_depth(spark):
    rare = spark.createDataFrame([(1, 3, [11, 12, 13, 14, 15]), (2, 3, [12, 13, 14, 15, 16])], "d long, p int, rare array<long>")
    rows = rare.select(F.explode(F.expr("slice(rare, 1, p)")).alias("key"), "d").withColumn("used", F.array("key"))
    for depth in (1, 2, 3):
        keys = [tuple(r.used) for r in rows.where("d = 1").collect()]
        assert len({frozenset(k) for k in keys}) == len(keys)
        marked = order_minhash.with_before(rows, rare)
        one, two = marked.where("d = 1"), marked.where("d = 2").withColumnRenamed("before", "before2").select("key", "before2")
        met = one.join(two, "key").where("NOT arrays_overlap(before, before2)").collect()
        assert [tuple(r.used) for r in met] == [(12, 13, 14)[:depth]]
        rows = order_minhash.rarer_keys(rows, rare, depth + 1)


def test_components_on_the_driver_and_distributed(spark):
    edges = spark.range(400).select((F.col("id") * 7 % 90).alias("a"), (F.col("id") * 7 % 90 + F.col("id") % 3 * 100).alias("b"))
    here = {(r.node, r.component) for r in components(Scratch(spark, "test"), edges).collect()}
    there = {(r.node, r.component) for r in components(Scratch(spark, "test"), edges, held_edges=0).collect()}
    assert here == there and len(here) > 90


def test_a_bucket_goes_on_by_more_keys_only_where_that_is_less_work(spark, monkeypatch):
    rng = np.random.default_rng(4)
    own = lambda n: [f"w{x}" for x in rng.integers(0, 40, n)]
    shared = ["is", "one"] * 60
    texts = [own(80) + shared for _ in range(30)]
    texts += [[*t[:70], *own(10), *shared] for t in texts[:10]]
    docs = spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate(texts)], "doc_id long, text string")
    monkeypatch.setattr(order_minhash, "RARE_WORK", 0)
    made = []
    deeper = order_minhash.rarer_keys

    def rarer_keys(rows, rare, depth):
        more = deeper(rows, rare, depth)
        for r in more.join(rare, "d").collect():
            assert r.ahead == r.p + depth - (r.rare.index(r.used[-1]) + 1)
        made.append(depth)
        return more

    monkeypatch.setattr(order_minhash, "rarer_keys", rarer_keys)
    found = {tuple(r) for r in order_minhash.near_duplicates(docs).select("doc_id", "cluster_id").collect()}
    assert made == []
    # the same classes where every bucket goes on as far as it can
    monkeypatch.setattr(order_minhash, "PER_KEY", 0)
    assert found == {tuple(r) for r in order_minhash.near_duplicates(docs).select("doc_id", "cluster_id").collect()}
    assert made == [2, 3] and len({c for _, c in found}) <= 30


def test_tiles_find_the_same_classes_and_fewer_links_than_pairs(spark, monkeypatch):
    rng = np.random.default_rng(9)
    shared = ["is", "one"] * 50
    bases = [[f"w{x}" for x in rng.integers(0, 60, 60)] for _ in range(4)]
    texts = []
    for base in bases:
        for k in range(20):
            t = list(base)
            for at in rng.choice(60, 12, replace=False):
                t[at] = f"own{k}_{at}"
            texts.append([*t, *shared])
    docs = spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate(texts)], "doc_id long, text string")
    made = []
    tiled = order_minhash.Search.tiled

    def counted(self, rows):
        before = self.known.count()
        tiled(self, rows)
        made.append(self.known.count() - before)

    monkeypatch.setattr(order_minhash.Search, "tiled", counted)
    monkeypatch.setattr(order_minhash, "WORK", 0)
    found = []
    for tile in (256, 16):
        monkeypatch.setattr(order_minhash, "TILE", tile)
        found.append({tuple(r) for r in order_minhash.near_duplicates(docs).select("doc_id", "cluster_id").collect()})
    assert len(made) == 4 and max(made) < 80 * 79 // 2
    # every pair compared by a join
    monkeypatch.setattr(order_minhash, "WORK", 1 << 30)
    found.append({tuple(r) for r in order_minhash.near_duplicates(docs).select("doc_id", "cluster_id").collect()})
    assert found[0] == found[1] == found[2]


def test_a_tile_links_what_is_near_by_few_pairs():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 2**32, 100, dtype=np.uint64).astype("<u4")
    words = []
    for k in range(60):
        t = base.copy()
        edits = 10 if k < 40 else 60
        t[rng.choice(100, edits, replace=False)] = rng.integers(0, 2**32, edits, dtype=np.uint64)
        words.append(t)
    bits = order_minhash.bitmaps(words)
    ids = np.arange(60)
    columns = {"d": ids, "c": ids, "top": np.full(60, 0), "n": np.full(60, 100), "is_left": ids > 0, "is_right": np.ones(60, bool)}
    tile = pa.table({**columns, "bits": pa.array(bits.tolist(), pa.list_(pa.int64())), "before": pa.array([[]] * 60, pa.list_(pa.int64())), "words": [t.tobytes() for t in words]})
    found = order_minhash.connected(tile, 0.8).to_pylist()
    pairs = [(i, j) for i in range(60) for j in range(i + 1, 60)]
    near = [p for p, (close, _) in zip(pairs, order_minhash.near([(words[i], words[j]) for i, j in pairs], 0.8), strict=True) if close]
    assert {(r["a"], r["b"]) for r in found} <= set(near) and len(found) < len(near)

    def parts(links):
        nodes, label = components_of(*np.array(sorted(links)).T)
        return dict(zip(nodes.tolist(), label.tolist(), strict=True))

    assert parts({(r["a"], r["b"]) for r in found}) == parts(set(near))
    # what a text shares with another before this key leaves the pair to that key
    met = tile.set_column(tile.schema.get_field_index("before"), "before", pa.array([[7]] * 60, pa.list_(pa.int64())))
    assert order_minhash.connected(met, 0.8).num_rows == 0
