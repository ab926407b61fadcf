"""Range-query workloads: boxes of uniform area or uniform weight, and their exact answers."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangekeep.operators import kdtree
from rangekeep.sources.shared import small

BOX = "query_id int, rect_id int, x_lo bigint, x_hi bigint, y_lo bigint, y_hi bigint"


def _u(*key) -> float:
    return int(hashlib.md5("|".join(map(str, key)).encode()).hexdigest()[:13], 16) / (1 << 52)


def uniform_area(wide: int, high: int, queries: int, rects: int, scale: float, seed: int = 1) -> list[tuple]:
    """Boxes with sides uniform up to scale times the domain's, anywhere they fit, disjoint within a query.

    A box that can't be placed in 200 tries is halved and tried again.
    """
    out = []
    for q in range(queries):
        held: list[tuple] = []
        for r in range(rects):
            most = [scale * wide, scale * high]
            for attempt in range(200_000):
                if attempt and attempt % 200 == 0:
                    most = [m / 2 for m in most]
                a, b, c, d = (_u("area", seed, q, r, attempt, k) for k in range(4))
                w, h = max(1, round(a * most[0])), max(1, round(b * most[1]))
                x, y = int(c * (wide - w + 1)), int(d * (high - h + 1))
                if all(x + w <= o[0] or o[1] <= x or y + h <= o[2] or o[3] <= y for o in held):
                    held.append((x, x + w, y, y + h))
                    out.append((q, r, x, x + w, y, y + h))
                    break
    return out


def uniform_weight(x: np.ndarray, y: np.ndarray, w: np.ndarray, wide: int, high: int, level: int, queries: int, rects: int, seed: int = 1, first_axis: int = 1, jitter: bool = False) -> list[tuple]:
    """Boxes drawn among the cells of one level of a kd tree over all keys, built apart from any sampler's tree."""
    off = (lambda node: 0.35 + 0.3 * _u("jitter", seed, node)) if jitter else None
    tree, _ = kdtree.build([x, y], w.astype(np.float64), first_axis=first_axis, depth=level, jitter=off)
    cells = list(kdtree.leaf_boxes(tree, [0, 0], [wide, high]).values())
    out = []
    for q in range(queries):
        order = sorted(range(len(cells)), key=lambda i: _u("weight", seed, level, q, i))
        out += [(q, r, int(cells[i][0][0]), int(cells[i][0][1]), int(cells[i][1][0]), int(cells[i][1][1])) for r, i in enumerate(order[:rects])]
    return out


def frame(spark: SparkSession, boxes: list[tuple]) -> DataFrame:
    return spark.createDataFrame(boxes, BOX)


def values(boxes: list[tuple]) -> str:
    """The boxes as SQL, under the name boxes."""
    rows = ", ".join(f"({', '.join(map(str, b))})" for b in boxes)
    return f"boxes AS (SELECT * FROM (VALUES {rows}) AS t(query_id, rect_id, x_lo, x_hi, y_lo, y_hi))"


def exact_boxes(points: DataFrame, boxes: DataFrame, x: str, y: str, w: str, cell_x: int = 0, cell_y: int = 0) -> DataFrame:
    """(query_id, exact, total): true sums. With cells given, boxes are cut into grid cells and meet points by equality;
    otherwise every point is tried against the boxes."""
    inside = (F.col(x) >= F.col("x_lo")) & (F.col(x) < F.col("x_hi")) & (F.col(y) >= F.col("y_lo")) & (F.col(y) < F.col("y_hi"))
    if cell_x and cell_y:
        span = lambda lo, hi, n: F.explode(F.sequence(F.floor(F.col(lo) / n), F.floor((F.col(hi) - 1) / n)))
        cut = boxes.select("*", span("x_lo", "x_hi", cell_x).alias("gx")).select("*", span("y_lo", "y_hi", cell_y).alias("gy"))
        rows = points.withColumn("gx", F.floor(F.col(x) / cell_x)).withColumn("gy", F.floor(F.col(y) / cell_y)).join(cut, ["gx", "gy"]).where(inside)
    else:
        rows = points.join(small(boxes), inside)
    sums = rows.groupBy("query_id").agg(F.sum(w).alias("e"))
    return boxes.select("query_id").distinct().join(sums, "query_id", "left").select("query_id", F.coalesce("e", F.lit(0)).cast("bigint").alias("exact"))
