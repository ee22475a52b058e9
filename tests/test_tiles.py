"""Counts over tiles of the pair matrix against plain counting."""

import numpy as np
import pyarrow as pa
import pytest

from pairsample.functions.measures import MEASURES, all_of
from pairsample.operators import baselines, baskets, refining, reporting, rules, sampling, tiles
from pairsample.plans import cost


@pytest.fixture(scope="module")
def rows(spark):
    rng = np.random.default_rng(5)
    found = {(int(t), f"x{i}") for t in range(300) for i in rng.zipf(1.3, 12) % 150} | {(1000 + t, f"x{i}") for t in range(3) for i in range(150)}
    return spark.createDataFrame(sorted(found), "t long, i string")


def test_pairs_and_samples_of_tiles(rows):
    items = tiles.numbered(rows)
    as_set = lambda df: {tuple(r) for r in df.select("i", "j", "k", "ci", "cj").collect()}
    for width in (16, 64, 4096):
        assert as_set(tiles.tile_pairs(rows, items, width=width)) == as_set(baselines.all_pairs(rows))
        assert as_set(tiles.tile_sample(rows, items, "lift", 3.0, 2.0, 7, width)) == as_set(sampling.sample_pairs(rows, "lift", 3.0, 2.0, 7, "selfjoin"))


def test_exact_pairs_and_cost_shuffle_no_pair(rows):
    for made in (baselines.exact_pairs(rows, "cosine", 0.2), cost.pair_sums(rows, "cosine", 15.0, 0.5)):
        plan = made._jdf.queryExecution().executedPlan().toString()
        assert "hashpartitioning(i" not in plan and "hashpartitioning(j" not in plan and "SortMergeJoin" not in plan and "hashpartitioning(t" in plan


def test_verifying_and_rules_by_tiles(rows):
    found = reporting.report(sampling.sample_pairs(rows, "cosine", 15.0, 0.3), "cosine", 15.0, 0.3)
    large = refining.verify_exact(found, rows, "cosine", 0.3, in_memory_rows=10)
    assert "hashpartitioning(t, j" not in large._jdf.queryExecution().executedPlan().toString()
    assert set(large.collect()) == set(refining.verify_exact(found, rows, "cosine", 0.3).collect()) != set()
    assert set(rules.rules_sampled(rows, 0.9).collect()) <= set(rules.rules_exact(rows, 0.9).collect())


def test_similarities_are_those_of_the_sql_texts(spark):
    k, ci, cj = np.array([1.0, 4.0, 9.0]), np.array([3.0, 5.0, 11.0]), np.array([7.0, 5.0, 29.0])
    for of in MEASURES.values():
        sql = spark.createDataFrame([(float(a), float(b), float(c)) for a, b, c in zip(k, ci, cj, strict=True)], "k double, ci double, cj double").selectExpr(of.sim_sql(m="77e0"))
        assert [r[0] for r in sql.collect()] == tiles.similarity(of, k, ci, cj, 77.0).tolist()


def test_no_rows(spark):
    empty = spark.createDataFrame([], "t long, i long")
    assert baselines.exact_pairs(empty, "cosine", 0.5).collect() == []
    assert cost.pair_sums(empty, "cosine", 15.0, 0.5).first()["distinct_pairs"] == 0


def test_sampled_minhash_shuffles_no_pair(rows):
    plain = refining.filter_minhash(sampling.sample_pairs(rows, "cosine", 15.0, 0.3), refining.minhash_sketch(rows, 16), 16, "cosine", 0.3)
    made = refining.sampled_minhash(rows, 16, "cosine", 15.0, 0.3, width=64)
    assert "hashpartitioning(i" not in made._jdf.queryExecution().executedPlan().toString()
    assert set(made.collect()) == set(plain.collect()) != set()


def test_samples_by_tiles_are_those_of_the_self_join(rows):
    both = all_of([("cosine", 0.7, 1.0), ("lift", 2.0, 1.0)])
    for of in (both, "cosine", "lift"):
        made = sampling.sample_pairs(rows, of, 2.0, 1.0, 3, "tiles")
        plan = made._jdf.queryExecution().executedPlan().toString()
        assert "hashpartitioning(i" not in plan and "hashpartitioning(t" in plan
        as_set = lambda df: {tuple(r) for r in df.select("i", "j", "k", "ci", "cj").collect()}
        assert as_set(made) == as_set(sampling.sample_pairs(rows, of, 2.0, 1.0, 3, "selfjoin")) != set()
    assert sampling.sample_pairs(rows.where("t < 0"), both, 2.0, 1.0, 3, "tiles").collect() == []


def test_transactions_above_all_chances_of_a_tile_are_not_dealt():
    batch = pa.RecordBatch.from_arrays([pa.array([[0, 1, 5], [0, 5], [4, 5]], pa.list_(pa.int32())), pa.array([0.1, 0.5, 0.9])], names=["a", "r"])
    dealt = [x for part in tiles._deal(4, 2, np.array([0.2, 0.4, 1.0]))([batch]) for x in part.to_pylist()]
    assert sorted((x["tile"], np.frombuffer(x["r"]).tolist()) for x in dealt) == [(0, [0.1]), (1, [0.1]), (2, [0.9])]


def test_pairs_that_reach_a_threshold_and_samples_of_many_blocks(rows):
    items = tiles.numbered(rows)
    for name, delta in (("cosine", 0.5), ("jaccard", 0.4), ("overlap", 0.8), ("all_confidence", 0.4), ("lift", 3.0)):
        m = baskets.transactions(rows)
        wanted = set(refining._reaching(baselines.all_pairs(rows), tiles.get(name), delta, m).collect())
        for width in (8, 16):
            made = refining._reaching(tiles.tile_pairs(rows, items, name, delta, width=width), tiles.get(name), delta, m)
            assert set(made.collect()) == wanted != set()
        sample = {tuple(r) for r in tiles.tile_sample(rows, items, name, 3.0, delta, 11, 8).select("i", "j", "k", "ci", "cj").collect()}
        assert sample == {tuple(r) for r in sampling.sample_pairs(rows, name, 3.0, delta, 11, "selfjoin").select("i", "j", "k", "ci", "cj").collect()}


def test_many_items_are_sent_to_few_tiles(rows):
    items = pa.table({"i": [f"y{n}" for n in range(500_000)], "c": np.full(500_000, 100)})
    plan = tiles.over_tiles(rows, items, None, "n long")._jdf.queryExecution().executedPlan().toString()
    # eight runs, to each of which a row goes as often: before, a row went to 123 of 7,626 tiles
    assert "(tile" in plan and ", 36)" in plan


def test_verified_candidates_are_not_shuffled_where_few_pairs_are_true(rows, spark, tmp_path, monkeypatch):
    found = reporting.report(sampling.sample_pairs(rows, "cosine", 15.0, 0.3, 42, "tiles"), "cosine", 15.0, 0.3)
    wanted = set(refining.verify_exact(found, rows, "cosine", 0.3).collect())
    spark.sparkContext.setCheckpointDir(str(tmp_path))
    made = refining.verify_exact(found, rows, "cosine", 0.3, in_memory_rows=10)
    plan = made._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" not in plan and "BroadcastHashJoin" in plan
    assert set(made.collect()) == wanted != set()
    monkeypatch.setattr(refining, "SENT", 1)
    assert set(refining.verify_exact(found, rows, "cosine", 0.3, in_memory_rows=10).collect()) == wanted


def test_points_of_all_views_are_planned_one_by_one(spark):
    from pairsample.plans.queries import _one_by_one

    seen = []

    def of(name):
        seen.append((name, len(spark.sparkContext._jsc.sc().statusTracker().getJobIdsForGroup(None))))
        return spark.createDataFrame([(name, 1.5)], "view string, x double").repartition(2)

    made = _one_by_one(spark, of, ("a", "b", "c"))
    assert "Exchange" not in made._jdf.queryExecution().executedPlan().toString() and [x for x, _ in seen] == ["a", "b", "c"]
    # the rows of a view are there before the next one is planned
    assert seen[0][1] < seen[1][1] < seen[2][1]
    assert [tuple(r) for r in made.collect()] == [("a", 1.5), ("b", 1.5), ("c", 1.5)]


def test_sides_hold_their_items_block_by_block():
    side = tiles.Side(np.array([3, 2]), np.array([0, 5, 6, 1, 9], np.uint16), 5, 3)
    assert [[x.tolist() for x in side.block(b)] for b in range(3)] == [[[0, 1], [1, 1], [0, 1]], [[0, 1], [2, 1], [0, 1, 4]], [[], [], []]]
