"""The experiments' directions on tables with enough keys, and the pieces they are made of on small ones."""

import pytest
from conftest import same

from rangekeep import registry
from rangekeep.plans import experiments as X
from rangekeep.plans import planes as P
from rangekeep.plans import workloads as W

MORE = "/root/testdata/sf0.01"


@pytest.mark.parametrize("name", ["accuracy_aware_vs_oblivious", "acc_directions", "boundary_cells_kd", "boxes_weight_inv"])
def test_directions(spark, duck, name):
    assert same(registry.queries()[name](spark, MORE).toPandas(), duck(registry.oracle_sql()[name], MORE)), name


def test_errors_of_a_whole_sample_are_none(spark, data):
    """A sample of all keys answers every battery exactly; a query that no sampled key meets counts as zero."""
    p = P.plane(spark, data, "docs")
    b = X.Batteries(p, {"area": X.area(p, 5, 3, 0.5), "cells": P.weight_boxes(P.weight_cells(p, 2), 2, 4, 2)})
    truth = {r.query_id: r.exact for r in b.truth.collect()}
    assert len(truth) == 9
    rows = {(r.setting, r.method): r for r in X.run(b, [p.n + 5], ("oblivious",), seeds=1).collect()}
    assert rows[("area", "oblivious")].abs_error == rows[("cells", "oblivious")].abs_error == 0
    none = spark.createDataFrame([], "method string, s int, seed int, query_id int, est double")
    lost = {r.setting: r for r in b.errors(none, spark.createDataFrame([("x", 1, 0)], "method string, s int, seed int")).collect()}
    assert lost["area"].abs_error == pytest.approx(lost["area"].share) and lost["cells"].rel_error == pytest.approx(1.0)


def test_cells_of_a_sampled_tree_cover_the_plane(spark, data):
    """The workload's tree may come from a bounded draw of the keys; its cells still hold every key once."""
    p = P.plane(spark, data, "pairs")
    for most in (100, 10**6):
        cells = P.weight_cells(p, 3, most=most)
        rows = P.truth(p, W.frame(spark, [(i, 0, *map(int, c)) for i, c in enumerate(cells)])).collect()
        assert len(cells) == 8 and sum(r.exact for r in rows) == p.total


def test_digest_is_fitted(spark, data):
    p = P.plane(spark, data, "docs")
    for s in (10, 60):
        nodes = X.fitted_digest(p, s)
        assert 1 <= nodes.count() <= s and nodes.agg({"units": "sum"}).first()[0] == p.total


def test_costs_are_reported(spark, data):
    built = {r["method"]: r for r in X.build_times(spark, data, (20,), "docs")}
    p = P.plane(spark, data, "docs")
    bx, by = p.bits
    assert built["wavelet"]["touched"] == p.n * (bx + 1) * (by + 1) and built["aware"]["touched"] == p.n and built["aware"]["bytes"] == 240
    assert built["wavelet"]["made"] > p.n and {r["method"] for r in X.query_times(spark, data, (20,), "docs", 4, 3)} == {"data", "aware", "oblivious", "wavelet", "qdigest", "sketch"}


def test_samples_of_a_plane_are_drawn_once(spark, data, monkeypatch):
    """Experiments over one plane share their samples, and their errors are those of samples drawn anew."""
    calls, draw = [], X.draw
    monkeypatch.setattr(X, "draw", lambda p, s, seed, *how: calls.append((s, seed, *how)) or draw(p, s, seed, *how))
    how = {"queries": 3, "seeds": 2}
    p = P.plane(spark, data, "pairs")
    shared = X.errors_of(X.error_vs_size(spark, data, p, (100,), ("aware", "oblivious"), **how))
    sweep = X.errors_of(X.guide_sweep(spark, data, p, 100, (1, 5), **how))
    assert len(calls) == len(set(calls)) == 6  # two seeds of two methods, and of the one factor that is new
    assert shared == pytest.approx(X.errors_of(X.error_vs_size(spark, data, "pairs", (100,), ("aware", "oblivious"), **how)))
    assert sweep[("area", "aware x5", 100)] == pytest.approx(shared[("area", "aware", 100)])
