"""Grid histograms, with cells of equal width or of about equal depth."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangekeep.sources.shared import small


def grid(points: DataFrame, x: str, y: str, w: str, cell_x: int, cell_y: int) -> DataFrame:
    """(gx, gy, units) of cells cell_x wide and cell_y high."""
    at = lambda c, n: F.floor(F.col(c) / n).cast("bigint")
    return points.groupBy(at(x, cell_x).alias("gx"), at(y, cell_y).alias("gy")).agg(F.sum(w).alias("units"))


def equidepth(points: DataFrame, x: str, y: str, w: str, cells: int, accuracy: int = 10_000) -> DataFrame:
    """(gx, gy, units, points): each axis cut at approximate quantiles of its points."""
    qs = [i / cells for i in range(1, cells)]
    cuts = points.agg(F.percentile_approx(x, qs, accuracy).alias("x"), F.percentile_approx(y, qs, accuracy).alias("y")).first()
    at = lambda c, v: F.size(F.filter(F.array(*[F.lit(k) for k in sorted(set(v or []))]), lambda k: k < F.col(c)))
    return points.groupBy(at(x, cuts.x).alias("gx"), at(y, cuts.y).alias("gy")).agg(F.sum(w).alias("units"), F.count("*").alias("points"))


def query(cells: DataFrame, boxes: DataFrame, cell_x: int, cell_y: int) -> DataFrame:
    """(query_id, est): cells of a grid by their share of area in each box."""
    ox = F.least(F.col("x_hi"), (F.col("gx") + 1) * cell_x) - F.greatest(F.col("x_lo"), F.col("gx") * cell_x)
    oy = F.least(F.col("y_hi"), (F.col("gy") + 1) * cell_y) - F.greatest(F.col("y_lo"), F.col("gy") * cell_y)
    rows = small(boxes).join(cells, (ox > 0) & (oy > 0))
    sums = rows.groupBy("query_id").agg(F.sum(F.col("units") * (ox * oy) / float(cell_x * cell_y)).alias("e"))
    return boxes.select("query_id").distinct().join(sums, "query_id", "left").select("query_id", F.coalesce("e", F.lit(0.0)).alias("est"))
