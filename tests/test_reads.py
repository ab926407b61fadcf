"""Queries that made up their rows read a given table, and totals are whole to the unit."""

import pytest
from pyspark.sql import functions as F

from rangekeep import registry
from rangekeep.operators.estimate import whole_total


@pytest.mark.parametrize("name", ["boundary_cells", "boxes_area", "dyadic_cover", "hypercube_cells", "join_theta", "udtf_dyadic"])
def test_reads_lineitem(spark, data, name):
    assert any("lineitem" in f for f in registry.queries()[name](spark, data).inputFiles())


def test_theory_follows_the_table(spark, tmp_path):
    rows = [("R", 1.0), ("N", 3.0)]
    spark.createDataFrame(rows, "l_returnflag string, l_extendedprice double").write.parquet(str(tmp_path / "lineitem.parquet"))
    got = {(r.s, r.d): r.oblivious for r in registry.queries()["bounds_theory"](spark, str(tmp_path)).collect()}
    assert got[(100, 2)] == 5.0


def test_total_of_many_weights_is_whole(spark):
    """2,700 times W / 2700, added as doubles, misses most W near 2^47."""
    for w in (139_000_000_000_001, 141_234_567_890_123, 144_999_999_999_997):
        rows = spark.range(2700).select(F.lit(w / 2700).alias("adj_weight"))
        assert rows.agg(whole_total().alias("t")).first().t == w


@pytest.mark.parametrize("w", [1_234_567_891, 2_999_999_939, 3_123_456_781, 987_654_321])
def test_quantile_where_the_running_weight_meets_it(spark, w):
    """A quarter, half and nine tenths of 300 equal weights are reached by the 75th, 150th and 270th."""
    from types import SimpleNamespace

    from rangekeep.operators.estimate import est_quantile

    rows = spark.range(300).select("id", F.col("id").cast("string").alias("hk"), F.lit(w / 300).alias("adj_weight"))
    got = {r.q: r.value for r in est_quantile(SimpleNamespace(rows=rows), "id", [0.25, 0.5, 0.9]).collect()}
    assert got == {0.25: 74, 0.5: 149, 0.9: 269}
