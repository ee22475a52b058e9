"""The worked example, agreement of the strategies, the error table and the rules, on small inputs."""

import math
import random

import pytest

from pairsample import api
from pairsample.functions import errors
from pairsample.functions.measures import MEASURES, get
from pairsample.operators import adaptive, baselines, baskets, refining, reporting, rules, sampling, two_pass, weighted
from pairsample.plans import cost


@pytest.fixture(scope="module")
def small(spark):
    rng = random.Random(1)
    rows = {(t, i) for t in range(120) for i in range(25) if rng.random() < 0.1 + 0.5 * (i % 5 == t % 5) + 0.02 * i / 25}
    return spark.createDataFrame(sorted(rows), "t long, i long").cache()


def as_set(df):
    return {tuple(r) for r in df.collect()}


def test_worked_example(spark):
    from pairsample.plans.queries import worked_example

    found = as_set(worked_example(spark, ""))
    assert {(i, j) for r, i, j in found if r == 0.9} == {(6, 5), (6, 4), (6, 3), (6, 2), (6, 1), (5, 4), (5, 3), (4, 3)}
    assert {(i, j) for r, i, j in found if r == 0.91} == {(6, 5), (6, 4), (6, 3), (6, 2), (6, 1), (5, 4)}


def test_report_step_of_the_example(spark):
    supports = {1: 60, 2: 60, 3: 50, 4: 5, 5: 5, 6: 3}
    rows = [(i, j, k, supports[i], supports[j]) for i, j, k in ((6, 5, 3), (6, 4, 2), (6, 1, 1), (5, 4, 4))]
    sample = spark.createDataFrame(rows, "i long, j long, k long, ci long, cj long")
    assert {(r.i, r.j) for r in reporting.report(sample, "cosine", 10.0, 0.7).collect()} == {(6, 5), (5, 4)}


def test_rules_differ_for_exact_pairs(spark):
    sample = spark.createDataFrame([(1, 2, 8, 100, 100)], "i long, j long, k long, ci long, cj long")
    assert reporting.report(sample, "cosine", 15.0, 0.14).count() == 1
    assert reporting.report(sample, "cosine", 15.0, 0.14, "strict").count() == 0


@pytest.mark.parametrize("measure,delta", [("cosine", 0.5), ("jaccard", 0.3), ("lift", 1.5), ("overlap", 0.6), ("all_confidence", 0.4)])
def test_strategies_agree(small, measure, delta):
    want = as_set(sampling.sample_pairs(small, measure, 3.0, delta, strategy="selfjoin"))
    assert want
    for strategy in ("prefix", "arrow", "shuffle", "blocked"):
        assert as_set(sampling.sample_pairs(small, measure, 3.0, delta, strategy=strategy, block=4)) == want, strategy


def test_exact_regime_counts(small):
    exact = {(r.i, r.j): r.k for r in baselines.all_pairs(small).collect()}
    sure = sampling.sample_pairs(small, "cosine", 1e6, 0.5)
    assert {(r.i, r.j): r.k for r in sure.collect()} == exact


def test_error_table():
    # fixed values: published miss probabilities
    for mu, p in ((3, 0.199), (5, 0.125), (10, 0.0671), (15, 0.0180), (20, 0.0108), (30, 0.00195)):
        assert errors.fn_poisson(mu) == pytest.approx(p, rel=0.01)
        assert errors.fn_poisson(mu) <= errors.fn_chernoff(mu)
    assert errors.fn_whole(10) == pytest.approx(0.0000454, rel=0.01)
    assert errors.fp_poisson(1 / 3, 15) == pytest.approx(0.133, abs=0.002)
    assert errors.mu_for(0.018) == pytest.approx(8 * math.log(1 / 0.018))
    assert errors.fn_binomial(1000, 0.015, 7.5) == pytest.approx(errors.fn_poisson(15), abs=0.002)


def test_measures_solve_their_equation():
    env = {"sqrt": math.sqrt, "greatest": max, "least": min}
    for name in ("cosine", "jaccard", "lift", "dice", "overlap", "all_confidence", "two_sided"):
        of = MEASURES[name]
        s = eval(of.sim("6.0", "10.0", "20.0", "100.0"), env)
        assert 6 * eval(of.weight("10.0", "20.0", repr(s), "100.0"), env) == pytest.approx(1)
        assert of.array(10.0, 20.0, s, 100.0) == pytest.approx(1 / 6)


def test_variants(small):
    want = as_set(baselines.exact_pairs(small, "cosine", 0.5).select("i", "j"))
    found = as_set(api.find_pairs(small, "cosine", 0.5, mu=30.0).select("i", "j"))
    assert found <= want and len(found) >= 0.9 * len(want)
    plain = reporting.report(sampling.sample_pairs(small, "cosine", 3.0, 0.5), "cosine", 3.0, 0.5)
    gated = reporting.report(two_pass.sample_two_pass(small, "cosine", 3.0, 0.5, width=64), "cosine", 3.0, 0.5)
    assert as_set(plain) == as_set(gated)
    assert as_set(two_pass.exact_two_pass(small, "cosine", 0.5, width=64).select("i", "j")) == want
    level = adaptive.levels(adaptive.occurrences(small, "cosine", 3.0, 0.3), "cosine", 3.0).where("level > 0.5")
    assert as_set(level.select("i", "j")) == as_set(plain.select("i", "j"))
    assert as_set(rules.rules_sampled(small, 0.6, 30.0)) <= as_set(rules.rules_exact(small, 0.6))


def test_global_weights_cancel(small, spark):
    one = small.selectExpr("t", "i", "1.0D AS w")
    other = small.selectExpr("t", "i", "CAST(1 + i % 3 AS DOUBLE) AS w")
    a, b = (as_set(weighted.exact_weighted(x, 0.4)) for x in (one, other))
    assert a == b and a


def test_cost_expectation(small):
    row = cost.compare(small, "cosine", 3.0, 0.5).first()
    assert row.time_s <= row.time_e and row.space_s <= row.space_e
    total = [sampling.sample_pairs(small, "cosine", 3.0, 0.5, seed=s).groupBy().sum("k").first()[0] for s in range(6)]
    assert sum(total) / 6 + small.count() == pytest.approx(row.time_s, rel=0.15)


def test_sketch_filter_keeps_similar_pairs(small):
    found = sampling.sample_pairs(small, "cosine", 15.0, 0.5)
    kept = refining.filter_minhash(found, refining.minhash_sketch(small, 64), 64, "cosine", 0.3)
    assert as_set(baselines.exact_pairs(small, "cosine", 0.7).select("i", "j")) <= as_set(kept.select("i", "j"))


def test_edges(spark):
    empty = spark.createDataFrame([], "t long, i long")
    assert sampling.sample_pairs(empty, "cosine", 15.0, 0.5).count() == 0
    dirty = spark.createDataFrame([(1, 1), (1, 1), (1, None), (None, 2), (2, 5)], "x long, y long")
    clean = baskets.as_baskets(dirty, "x", "y")
    assert as_set(clean) == {(1, 1), (2, 5)}
    assert sampling.sample_pairs(clean, "jaccard", 15.0, 0.5).count() == 0
    with pytest.raises(ValueError):
        sampling.sample_pairs(clean, "cosine", 15.0, 0.5, scope="anchor")


def test_plan_has_no_cross_product(small):
    plan = sampling.sample_pairs(small, "cosine", 15.0, 0.5)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
    assert get("cosine").uses_m is False


def test_a_falling_threshold_stops_after_enough_results(small):
    full = {(r.i, r.j): r.level for r in adaptive.levels(adaptive.occurrences(small, "cosine", 15.0, 0.0625), "cosine", 15.0).collect()}
    floors = [1.0 * 0.5**k for k in range(1, 5)]
    for wanted in (1, 10, 40):
        floor = next((f for f in floors if sum(x > f for x in full.values()) >= wanted), floors[-1])
        got = {(r.i, r.j): r.level for r in adaptive.enough_pairs(small, "cosine", 15.0, wanted, least=0.0625).collect()}
        assert got == pytest.approx({p: x for p, x in full.items() if x > floor})
    few = adaptive.top_pairs(small, "cosine", 15.0, 10, least=0.0625).collect()
    assert [r.level for r in few] == pytest.approx(sorted(full.values(), reverse=True)[:10], abs=1e-6)


def test_confusion_where_nothing_is_true_or_reported(spark):
    none, one = (spark.createDataFrame(rows, "i long, j long") for rows in ([], [(1, 2)]))
    for found, true, wanted in ((none, none, "0 0 0 nan nan"), (one, none, "0 1 0 nan 0.0"), (none, one, "0 0 1 0.0 nan"), (one, one, "1 0 0 1.0 1.0")):
        assert " ".join(str(x) for x in cost.confusion(found, true).first()) == wanted
