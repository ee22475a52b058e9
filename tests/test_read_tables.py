"""Queries on measures and error probabilities take their numbers from a given table."""

import duckdb
import pytest

from pairsample.plans import registry

NAMES = "fig5_mu_epsilon fig6_curves fn_binomial fp_curve mean_samples_identity measure_aliases measure_all_confidence measure_cosine measure_dice measure_jaccard measure_lift measure_monotone_check".split()
SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", NAMES)
def test_reads_lineitem_and_agrees_with_sql(spark, name):
    out = registry.queries()[name](spark, SF)
    assert any("lineitem.parquet" in f for f in out.inputFiles())
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{SF}/lineitem.parquet'")
    want = con.execute(registry.oracle_sql()[name]).fetchall()
    columns = [c[0] for c in con.description]
    assert sorted(map(tuple, out.select(*columns).collect())) == sorted(want) and want
