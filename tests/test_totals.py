"""Totals of samples whose whole weight has more bits than a double."""

from pathlib import Path

import pandas as pd
import pytest

from rangekeep import registry

SQL = registry.oracle_sql()


@pytest.fixture(scope="module")
def heavy_tables(tmp_path_factory):
    """1,600 orders and lines whose prices in hundredths are whole, differ and add up to some 2^59."""
    d = tmp_path_factory.mktemp("heavy")
    n, day = 1600, pd.Timestamp("1995-01-01")
    price = [(3 * 10**14 + 791_903 * i + i * i % 1_009) / 100 for i in range(n)]
    tables = {
        "nation": {"n_nationkey": range(25), "n_regionkey": [i % 5 for i in range(25)]},
        "customer": {"c_custkey": range(400), "c_nationkey": [i % 25 for i in range(400)]},
        "supplier": {"s_suppkey": range(40), "s_nationkey": [i % 25 for i in range(40)]},
        "part": {"p_partkey": range(40), "p_brand": [f"b{i % 5}" for i in range(40)], "p_type": [f"t{i % 8}" for i in range(40)]},
        "orders": {"o_custkey": [i % 400 for i in range(n)], "o_orderdate": [day + pd.Timedelta(days=i) for i in range(n)], "o_totalprice": price},
        "lineitem": {"l_partkey": [i // 40 for i in range(n)], "l_suppkey": [i % 40 for i in range(n)], "l_extendedprice": price},
    }
    for name, columns in tables.items():
        pd.DataFrame(columns).to_parquet(d / f"{name}.parquet", coerce_timestamps="us")
    return str(d)


@pytest.mark.parametrize("name", ["hier_prefix_bits", "kd_custday_inv", "kd_mixed_custday_inv", "two_pass_flows", "two_pass_mixed"])
def test_total_is_whole(spark, duck, heavy_tables, name):
    got, want = registry.queries()[name](spark, heavy_tables).first().asDict(), duck(SQL[name], heavy_tables).iloc[0].to_dict()
    assert want["total"] > 1 << 53
    assert {c: int(v) for c, v in got.items()} == {c: int(v) for c, v in want.items()}


@pytest.fixture(scope="module")
def repeated_tables(heavy_tables, tmp_path_factory):
    """The same tables with weights of about one size that add up to those of 80 copies of sf0.1's orders and 60 of its lines."""
    d = tmp_path_factory.mktemp("repeated")
    for p in Path(heavy_tables).glob("*.parquet"):
        t = pd.read_parquet(p)
        for price, total in (("o_totalprice", 300_187_130_068_480), ("l_extendedprice", 190_627_212_741_600)):
            if price in t:
                units = [total // len(t) + i * 791_903 - (len(t) - 1) * 791_903 // 2 for i in range(len(t))]
                units[0] += total - sum(units)
                t[price] = [u / 100 for u in units]
        t.to_parquet(d / p.name, coerce_timestamps="us")
    return str(d)


@pytest.mark.parametrize("name", ["kd_custday_inv", "hier_prefix_bits", "kd_mixed_custday_inv", "two_pass_flows"])
def test_total_of_equal_shares(spark, duck, repeated_tables, name):
    """A hundred or a thousand doubles of one value drift from their sum by whole units at these totals."""
    got, want = registry.queries()[name](spark, repeated_tables).first().asDict(), duck(SQL[name], repeated_tables).iloc[0].to_dict()
    assert want["total"] in (300_187_130_068_480, 190_627_212_741_600) and want["heavy"] == 0
    assert {c: int(v) for c, v in got.items()} == {c: int(v) for c, v in want.items()}


@pytest.fixture(scope="module", params=[3 * 10**12, 3 * 10**14])
def even_tables(request, heavy_tables, tmp_path_factory):
    """A hundred orders and a thousand lines of one weight beside one of a single unit: the threshold lies above the heavy ones
    by a fraction of a unit, so that none reaches it."""
    d = tmp_path_factory.mktemp("even")
    for p in Path(heavy_tables).glob("*.parquet"):
        t = pd.read_parquet(p)
        for price, n in (("o_totalprice", 100), ("l_extendedprice", 1000)):
            if price in t:
                t = t.iloc[: n + 1].assign(**{price: [request.param / 100] * n + [0.01]})
        t.to_parquet(d / p.name, coerce_timestamps="us")
    return str(d)


@pytest.mark.parametrize("name", ["hier_prefix_bits", "kd_custday_inv", "kd_mixed_custday_inv", "two_pass_flows"])
def test_keys_just_below_the_threshold(spark, duck, even_tables, name):
    got, want = registry.queries()[name](spark, even_tables).first().asDict(), duck(SQL[name], even_tables).iloc[0].to_dict()
    assert want["heavy"] == 0 and want["total"] % 100 == 1
    assert {c: int(v) for c, v in got.items()} == {c: int(v) for c, v in want.items()}
