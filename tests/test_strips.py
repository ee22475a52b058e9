"""Counts over strips of items against plain counting."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from pairsample.operators import adaptive, baselines, refining, sampling, strips, tiles
from pairsample.operators import baskets as bk
from pairsample.plans import cost


@pytest.fixture(scope="module")
def rows(spark):
    rng = np.random.default_rng(5)
    found = {(int(t), f"x{i}") for t in range(300) for i in rng.zipf(1.3, 12) % 150} | {(1000 + t, f"x{i}") for t in range(3) for i in range(150)}
    return spark.createDataFrame(sorted(found), "t long, i string")


def as_set(df):
    return {tuple(r) for r in df.select("i", "j", "k", "ci", "cj").collect()}


def test_pairs_of_strips(rows, monkeypatch):
    items = tiles.numbered(rows)
    wanted = as_set(baselines.all_pairs(rows))
    for n in (1, 5, None):
        assert as_set(strips.strip_pairs(rows, items, strips=n)) == wanted
    monkeypatch.setattr(strips, "ROOM", 50)
    assert as_set(strips.strip_pairs(rows, items)) == wanted


def test_too_many_items_for_tiles_shuffle_no_pair(rows, monkeypatch):
    by_tiles = cost.compare(rows, "lift", 3.0, 2.0).first()
    exact = set(baselines.exact_pairs(rows, "cosine", 0.2).collect())
    monkeypatch.setattr(tiles, "MAX_ITEMS", 10)
    monkeypatch.setattr(tiles.numbered, "__defaults__", (10,))
    monkeypatch.setattr(cost, "TILE_ITEMS", 10, raising=False)
    monkeypatch.setattr(baselines, "TILE_ITEMS", 10, raising=False)
    for made in (cost.pair_sums(rows, "lift", 3.0, 2.0), baselines.exact_pairs(rows, "cosine", 0.2)):
        plan = made._jdf.queryExecution().executedPlan().toString()
        assert "hashpartitioning(i" not in plan and "hashpartitioning(j" not in plan and "SortMergeJoin" not in plan
    assert cost.compare(rows, "lift", 3.0, 2.0).first() == by_tiles
    assert set(baselines.exact_pairs(rows, "cosine", 0.2).collect()) == exact


def test_levels_shuffle_no_pair(rows):
    for measure, floor in (("cosine", 0.4), ("lift", 2.0)):
        m = bk.transactions(rows) if measure == "lift" else None
        plain = adaptive.levels(adaptive.occurrences(rows, measure, 15.0, floor), measure, 15.0, m).where(F.col("level") > floor)
        made = adaptive.strip_levels(rows, tiles.numbered(rows), measure, 15.0, floor, strips=3)
        assert {tuple(r) for r in made.collect()} == {tuple(r) for r in plain.select("i", "j", "ci", "cj", "level").collect()} != set()
    plan = adaptive.enough_pairs(rows, "cosine", 15.0, 10)._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning(i" not in plan and "Window" not in plan


def test_sampled_smaller_set_shuffles_no_pair(rows):
    plain = refining.filter_smaller_set(sampling.sample_pairs(rows, "overlap", 15.0, 0.3), rows, 0.5, "overlap", 0.3)
    made = refining.sampled_smaller_set(rows, 0.5, "overlap", 15.0, 0.3, strips=3)
    assert "hashpartitioning(t, j" not in made._jdf.queryExecution().executedPlan().toString()
    assert set(made.collect()) == set(plain.collect()) != set()
