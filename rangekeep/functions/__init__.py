"""Uniform numbers and masses that Spark and DuckDB compute alike."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: One unit of probability in whole ticks, so that masses add exactly in any order.
UNIT = 1 << 40


def uniform(stage: str, seed: int, *keys: Column | str, portable: bool = True) -> Column:
    """A number in [0, 1) that depends on the tag, the seed and the keys alone; a retried task draws the same.

    The portable form is md5, which every engine has; the other is xxhash64, several times cheaper.
    """
    cols = [F.col(k) if isinstance(k, str) else k for k in keys]
    if not portable:
        return F.shiftrightunsigned(F.xxhash64(F.lit(stage), F.lit(seed), *cols), 11) / float(1 << 53)
    text = F.concat_ws("|", F.lit(stage), F.lit(str(seed)), *[c.cast("string") for c in cols])
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("bigint") / float(1 << 52)


def uniform_sql(stage: str, seed: int, *keys: str) -> str:
    text = " || '|' || ".join([f"'{stage}'", f"'{seed}'", *[f"CAST({k} AS VARCHAR)" for k in keys]])
    return f"(('0x' || substr(md5({text}), 1, 13))::BIGINT / 4503599627370496.0::DOUBLE)"


def ticks(p: Column) -> Column:
    return F.floor(p * float(UNIT) + 0.5).cast("bigint")


def ticks_sql(p: str) -> str:
    return f"floor(({p}) * {UNIT}.0::DOUBLE + 0.5::DOUBLE)::BIGINT"
