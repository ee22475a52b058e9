"""Vectors that share a band of signs, against plain comparison."""

import numpy as np
from pyspark.sql import functions as F

from pairsample.operators import baselines, vectors


def expected(rows, bits, bands, at_least):
    normals = baselines.planes(bands, bits, len(rows[0][1]))
    codes = {v: vectors.codes_of(np.array([x]), normals)[0] for v, x in rows}
    out = {}
    for v, x in rows:
        for w, y in rows:
            if v < w and (codes[v] == codes[w]).any():
                with np.errstate(all="ignore"):
                    cos = np.float64(np.dot(x, y)) / np.sqrt(np.float64(np.dot(x, x)) * np.dot(y, y))
                if not cos < at_least:
                    out[v, w] = cos
    return out


def test_hyperplane_pairs_against_plain_comparison(spark, monkeypatch):
    rng = np.random.default_rng(8)
    rows = [(int(v), rng.standard_normal(8).tolist()) for v in rng.permutation(400)]
    rows += [(1000, [0.0] * 8), (1001, [float("nan")] * 8), (1002, [1e200] * 8), (1003, rows[0][1])]
    want = expected(rows, 5, 6, 0.6)
    for block, columns in ((vectors.BLOCK, vectors.COLUMNS), (50, 16)):
        monkeypatch.setattr(vectors, "BLOCK", block)
        monkeypatch.setattr(vectors, "COLUMNS", columns)
        monkeypatch.setattr(vectors, "ROWS", columns)
        table = spark.createDataFrame([*rows, (2000, None), (2001, [1.0]), (None, rows[0][1])], "v long, x array<double>").repartition(3)
        # the first vector sets the number of components
        made = baselines.hyperplane_pairs(table.where("v <> 2001"), "v", "x", 5, 6, 0.6)
        got = {(r.i, r.j): r.cos for r in made.collect()}
        assert got.keys() == want.keys()
        assert all(np.isclose(got[p], want[p], atol=1e-6, equal_nan=True) for p in want)
    assert len(want) > 100


def test_hyperplane_pairs_shuffle_no_pair(spark):
    table = spark.range(300).select(F.col("id").alias("v"), F.expr("transform(sequence(1, 4), k -> CAST(sin(id * k) AS FLOAT))").alias("x"))
    plan = baselines.hyperplane_pairs(table, "v", "x", 4, 4, 0.9)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Aggregate" not in plan
    text = table.select(F.concat(F.lit("n"), "v").alias("v"), "x")
    named = {(r.i, r.j) for r in baselines.hyperplane_pairs(text, "v", "x", 4, 4, 0.9).collect()}
    assert named == {tuple(sorted((f"n{r.i}", f"n{r.j}"))) for r in baselines.hyperplane_pairs(table, "v", "x", 4, 4, 0.9).collect()} != set()
