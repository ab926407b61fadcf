"""Dyadic pieces of half-open integer intervals and boxes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def cover(lo: Column, hi: Column, bits: int) -> Column:
    """Array of structs (l, k): the fewest blocks [k 2^l, (k+1) 2^l) that make up [lo, hi). At most two a level."""

    def at(level: Column) -> Column:
        size = F.call_function("shiftleft", F.lit(1).cast("bigint"), level)
        first, last = F.ceil(lo / size).cast("bigint"), (F.floor(hi / size) - 1).cast("bigint")

        def whole(k: Column) -> Column:
            up = F.floor(k / 2).cast("bigint") * 2 * size
            inside = (k * size >= lo) & ((k + 1) * size <= hi) & (k >= 0)
            parent_inside = (up >= lo) & (up + 2 * size <= hi) & (level < bits)
            return inside & ~parent_inside

        found = F.filter(F.array_distinct(F.array(first, last)), whole)
        return F.transform(found, lambda k: F.struct(level.alias("l"), k.alias("k")))

    return F.flatten(F.transform(F.sequence(F.lit(0), F.lit(bits)), at))


def pieces(boxes: DataFrame, bits_x: int, bits_y: int) -> DataFrame:
    """A row for each dyadic rectangle of each box: query_id, rect_id, lx, kx, ly, ky."""
    xs = boxes.select("query_id", "rect_id", "y_lo", "y_hi", F.explode(cover(F.col("x_lo"), F.col("x_hi"), bits_x)).alias("px"))
    xy = xs.select("query_id", "rect_id", "px", F.explode(cover(F.col("y_lo"), F.col("y_hi"), bits_y)).alias("py"))
    return xy.select("query_id", "rect_id", F.col("px.l").alias("lx"), F.col("px.k").alias("kx"), F.col("py.l").alias("ly"), F.col("py.k").alias("ky"))
