"""What many seeds report, against the samples made as rows."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from pairsample.functions.measures import get
from pairsample.operators import baselines, reporting, sampling, seeds, tiles


@pytest.fixture(scope="module")
def rows(spark):
    rng = np.random.default_rng(6)
    found = {(f"t{t}", int(i)) for t in range(400) for i in rng.zipf(1.3, 12) % 60} | {(f"u{t}", i) for t in range(3) for i in range(60)}
    return spark.createDataFrame(sorted(found), "t string, i long")


MU, DELTA, SEEDS = 15.0, 0.3, range(1, 5)


@pytest.fixture(scope="module")
def samples(rows):
    return {s: sampling.sample_pairs(rows, "cosine", MU, DELTA, s, "selfjoin").cache() for s in SEEDS}


def reported(sample):
    return {(r.i, r.j) for r in sample.where(reporting.rule_sql(get("cosine"), MU, DELTA)).collect()}


def test_reports_by_similarity_shuffle_no_pair(rows, samples):
    made = seeds.reports_by_similarity(rows, tiles.numbered(rows), "cosine", MU, DELTA, SEEDS, strips=3)
    assert "hashpartitioning(i" not in made._jdf.queryExecution().executedPlan().toString()
    bucket = {(r.i, r.j): r.b for r in baselines.all_pairs(rows).withColumn("b", F.expr(f"CAST(floor({get('cosine').sim_sql()} / {DELTA}D * 10) AS INT)")).collect()}
    times = [bucket[p] for s in SEEDS for p in reported(samples[s])]
    assert {(r.bucket, r.pairs, r.reports) for r in made.collect()} == {(b, list(bucket.values()).count(b), times.count(b)) for b in bucket.values()}


def test_misses_of_seeds_shuffle_no_pair(rows, samples):
    made = seeds.missed_by_seed(rows, tiles.numbered(rows), "cosine", MU, DELTA, SEEDS, strips=3)
    assert "hashpartitioning(i" not in made._jdf.queryExecution().executedPlan().toString()
    true = {(r.i, r.j) for r in baselines.exact_pairs(rows, "cosine", DELTA).collect()}
    assert len(true) > 20
    assert {tuple(r) for r in made.collect()} == {(s, len(true), len(true - reported(samples[s]))) for s in SEEDS}


def test_insertions_of_seeds_make_no_pair(rows, samples):
    made = seeds.inserted_by_seed(rows, "cosine", MU, DELTA, SEEDS)
    assert "hashpartitioning(i" not in made._jdf.queryExecution().executedPlan().toString()
    assert {tuple(r) for r in made.collect()} == {(s, samples[s].agg(F.sum("k")).first()[0]) for s in SEEDS}
