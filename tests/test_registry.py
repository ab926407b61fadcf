"""Every query of the engine against its SQL on the smallest tables, and the entry point."""

import pytest
from conftest import same

from rangekeep import registry

SQL = registry.oracle_sql()
#: Directions of experiments need more keys than the smallest tables have; test_experiments runs them on more.
LARGE = {"accuracy_aware_vs_oblivious", "acc_directions", "boundary_cells_kd", "boxes_weight_inv"}


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(registry.queries()) <= set(e.queries()) and set(e.oracle_sql()) <= set(e.queries())


@pytest.mark.parametrize("name", sorted(set(SQL) - LARGE))
def test_query(spark, data, duck, name):
    assert same(registry.queries()[name](spark, data).toPandas(), duck(SQL[name], data)), name


@pytest.mark.parametrize("name", ["sample_builtin", "sample_by", "sample_table", "acc_docs_size"])
def test_rows_only(spark, data, name):
    assert registry.queries()[name](spark, data).count() >= 0
