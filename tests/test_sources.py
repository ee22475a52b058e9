"""Sources, sinks, SQL functions, and plans."""

import dataclasses
import math

from pyspark.sql import functions as F

from pairsample import api
from pairsample.functions import measures, sql_functions
from pairsample.operators import baselines, refining, reporting, sampling, two_pass
from pairsample.operators.baskets import known_supports, support_counts
from pairsample.plans import planner
from pairsample.sources import tables


def baskets_of(spark, n=40, items=12):
    return spark.createDataFrame([(t, i) for t in range(n) for i in range(items) if (t * 7 + i * i) % 5 < 2], "t long, i long")


def test_basket_lines(spark, tmp_path):
    (tmp_path / "lines.txt").write_text("a b c\nb c\n\nb c\na a\n")
    got = tables.read_basket_lines(spark, str(tmp_path / "lines.txt"))
    sizes = sorted(r.n for r in got.groupBy("t").agg(F.count("*").alias("n")).collect())
    assert sizes == [1, 2, 2, 3] and {r.i: r.c for r in support_counts(got).collect()} == {"a": 2, "b": 3, "c": 3}


def test_formats_and_sinks(spark, tmp_path):
    rows = baskets_of(spark)
    for fmt in ("parquet", "orc", "json", "csv"):
        tables.write(rows, str(tmp_path / fmt), fmt)
        assert sorted(tables.read(spark, fmt, str(tmp_path / fmt), "t long, i long").collect()) == sorted(rows.collect())
    tables.write(rows, str(tmp_path / "by_item"), partition_by=["i"])
    pruned = spark.read.parquet(str(tmp_path / "by_item")).where("i = 3")
    assert "PartitionFilters: [isnotnull(i" in pruned._jdf.queryExecution().executedPlan().toString() and pruned.count() == rows.where("i = 3").count()


def test_bucketed_supports_join_without_a_shuffle_of_their_own(spark):
    rows = baskets_of(spark)
    tables.save_support(support_counts(rows), "supports_of_test", 4)
    plan = rows.join(spark.table("supports_of_test").hint("merge"), "i")._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") <= 1
    spark.sql("DROP TABLE supports_of_test")


def test_sql_functions(spark):
    names = sql_functions.register_measures(spark)
    assert "sim_cosine" in names and "weight_lift" in names
    sim, weight = spark.sql("SELECT sim_cosine(6D, 9D, 16D, 1D), weight_cosine(9D, 16D, 0.5D, 1D)").first()
    assert math.isclose(sim, 0.5) and math.isclose(weight, 1 / 6)
    sql_functions.register_pairs_of(spark)
    got = spark.sql("SELECT * FROM pairs_of(array('1', '2', '3', '4', '5', '6'), array(60L, 60L, 50L, 5L, 5L, 3L), 0.91D, 0.7D, 10D, 1D)")
    assert {(int(r.i), int(r.j)) for r in got.collect()} == {(6, 5), (6, 4), (6, 3), (6, 1), (6, 2), (4, 5)}


def test_own_measure(spark):
    mine = measures.register_measure(dataclasses.replace(measures.get("cosine"), name="mine"))
    try:
        assert measures.get("mine") is mine
        assert measures.monotone_violations("mine", spark.createDataFrame([(4, 9, 0.5), (9, 16, 0.5)], "ci long, cj long, s double")).count() == 0
        rows = baskets_of(spark)
        assert sorted(sampling.sample_pairs(rows, "mine").collect()) == sorted(sampling.sample_pairs(rows, "cosine").collect())
    finally:
        del measures.MEASURES["mine"]


def test_verification_in_memory_equals_the_join(spark):
    rows = baskets_of(spark)
    found = reporting.report(sampling.sample_pairs(rows, "cosine", 15.0, 0.3), "cosine", 15.0, 0.3)
    one = refining.verify_exact(found, rows, "cosine", 0.3)
    two = refining.verify_exact(found.drop("exact"), rows, "cosine", 0.3, in_memory_rows=0)
    assert sorted(one.collect()) == sorted(two.collect()) and one.count() > 0
    assert sorted(one.collect()) == sorted(baselines.exact_pairs(rows, "cosine", 0.3).collect())


def test_count_min_gate_reports_the_same(spark):
    rows = baskets_of(spark, 200)
    plain = reporting.report(sampling.sample_pairs(rows, "cosine", 15.0, 0.3), "cosine", 15.0, 0.3)
    gated = reporting.report(two_pass.sample_count_min(rows, "cosine", 15.0, 0.3), "cosine", 15.0, 0.3)
    assert sorted(plain.collect()) == sorted(gated.collect())


def test_empty_baskets(spark):
    none = spark.createDataFrame([], "t long, i long")
    assert api.find_pairs(none).count() == 0 and known_supports(none).count() == 0


def test_plans(spark):
    rows = baskets_of(spark)
    text = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert planner.choose_strategy(rows, known_supports(rows)) == "arrow"
    # one pass over the transactions: a shuffle to pack them and one to count pairs, none for the supports
    plan = text(sampling.sample_pairs(rows, "cosine", support=known_supports(rows)))
    assert plan.count("Exchange hashpartitioning") == 2 and "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
    # a hot item is spread over its runs
    assert "salt" in text(support_counts(rows, "sort"))


def test_runs_of_words_are_shuffled_once(spark, tmp_path):
    from pairsample.plans import cost
    from pairsample.sources import workloads

    texts = ["a b c d e f a b c d e f", "b c d e f g", "x a b c d e", "  A  b c d e f ", "a b", None]
    spark.createDataFrame([*enumerate(texts), (0, texts[0])], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(0, "b c d e f g h")], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    made = workloads.baskets(spark, str(tmp_path), "run_texts")
    words = [(f"document {n}", t.lower().split()) for n, t in enumerate(texts) if t] + [("item 0", "b c d e f g h".split())]
    wanted = sorted({(" ".join(w[p : p + 5]), i) for i, w in words for p in range(len(w) - 4)})
    assert sorted(tuple(r) for r in made.collect()) == wanted
    plan = made.groupBy("t").count()._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning(t") == 1 and "hashpartitioning(t#" in plan and "i#" not in plan.split("hashpartitioning(")[1].split(")")[0]
    assert cost.base(made).first()["rows"] == len(wanted)
