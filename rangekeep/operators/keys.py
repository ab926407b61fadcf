"""Weighted key sets: one row per key, weights in whole units, a text form of the key as `hk`."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def units(w: Column | str, scale: int = 1) -> Column:
    w = F.col(w) if isinstance(w, str) else w
    return F.floor(w * scale + 0.5).cast("bigint")


def key_text(*key: str) -> Column:
    return F.concat_ws("|", *[F.col(k).cast("string") for k in key])


def keyed(df: DataFrame, key: list[str], w: str | Column, scale: int = 1, on_bad: str = "error", unique: bool = False, carry: list[str] | None = None) -> DataFrame:
    """(key..., carry..., hk, units) with each key once.

    A null or negative weight raises while the rows are read, or drops the row with on_bad="drop". Zero weights stay
    and are never sampled. With unique=True the caller vouches for unique keys and nothing is shuffled. carry names
    columns that the key determines. Rows with a null in the key are dropped, as they name no key.
    """
    w = F.col(w) if isinstance(w, str) else w
    keep = [*key, *(carry or [])]
    rows = df.select(*keep, w.alias("__w")).dropna(subset=key)
    bad = F.col("__w").isNull() | (F.col("__w") < 0) | F.isnan(F.col("__w").cast("double"))
    if on_bad == "drop":
        rows = rows.where(~bad)
    elif on_bad == "error":
        rows = rows.withColumn("__w", F.when(bad, F.raise_error(F.lit("a weight is null, negative or no number"))).otherwise(F.col("__w")))
    else:
        raise ValueError(on_bad)
    if unique:
        return rows.select(*keep, key_text(*key).alias("hk"), units("__w", scale).alias("units"))
    # sums of units pass 63 bits at 100 TB, hence the decimal; one key's own sum is cast back, and fails loudly if it can't be
    total = F.sum(units("__w", scale).cast("decimal(38,0)")).cast("bigint")
    firsts = [F.min(c).alias(c) for c in (carry or [])]
    return rows.groupBy(*key).agg(total.alias("units"), *firsts).select(*keep, key_text(*key).alias("hk"), "units")


def keyed_sql(src: str, key: list[str], w: str, scale: int = 1, carry: list[str] | None = None) -> str:
    """DuckDB's form of keyed() for rows without bad weights."""
    hk = " || '|' || ".join(f"CAST({k} AS VARCHAR)" for k in key)
    mins = "".join(f", min({c}) AS {c}" for c in carry or [])
    return f"SELECT {', '.join(key)}{mins}, {hk} AS hk, sum(floor(({w}) * {scale} + 0.5::DOUBLE)::BIGINT)::BIGINT AS units FROM {src} GROUP BY {', '.join(key)}"
