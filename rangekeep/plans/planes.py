"""Planes: key sets with two whole-number axes and a weight, on which boxes are asked, and workloads over them.

Nothing here gathers keys: bounds come from one aggregate, the tree of the uniform-weight workload is built over a
bounded sample (with the masses of its cells counted exactly in one scan), and truth is a binned join.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangekeep.operators import kdtree
from rangekeep.plans import workloads as W
from rangekeep.plans.sampling_queries import event_set, key_set
from rangekeep.sources.shared import keep

#: Keys over which the tree of a uniform-weight workload is built; cells are at most a few thousand.
TREE_KEYS = 50_000


@dataclass
class Plane:
    """keys (hk, units, x, y), the axes' exclusive bounds, the whole weight and how many keys there are."""

    keys: DataFrame
    wide: int
    high: int
    total: int
    n: int
    #: Samples drawn from the keys, by what decides them.
    drawn: dict = field(default_factory=dict, repr=False, compare=False)

    @property
    def bits(self) -> tuple[int, int]:
        return max(1, (self.wide - 1).bit_length()), max(1, (self.high - 1).bit_length())

    @property
    def points(self) -> DataFrame:
        return self.keys.select("x", "y", F.col("units").alias("w"))


def pairs(spark: SparkSession, d: str) -> DataFrame:
    """Parts by suppliers: the flows' stand-in."""
    return key_set(spark, d, "pairs").select("hk", "units", F.col("l_partkey").alias("x"), F.col("l_suppkey").alias("y"))


def events(spark: SparkSession, d: str) -> DataFrame:
    """Codes by users: the tickets' stand-in. An event type's place among the types heads its codes, so that a type is a stretch."""
    k = event_set(spark, d)
    types = [r.event_type for r in k.select("event_type").distinct().orderBy("event_type").collect()]  # a handful of names
    at = F.lit(0)
    for i, t in enumerate(types):
        at = F.when(F.col("event_type") == t, i).otherwise(at)
    return k.select("hk", "units", (at * 128 + F.col("code")).cast("bigint").alias("x"), F.col("user_id").cast("bigint").alias("y"))


def docs(spark: SparkSession, d: str) -> DataFrame:
    """Documents by length and number."""
    return key_set(spark, d, "docs").select("hk", "units", F.col("doc_id").alias("x"), F.least(F.col("units"), F.lit((1 << 20) - 1)).alias("y"))


PLANES = {"pairs": pairs, "events": events, "docs": docs}


def plane(spark: SparkSession, d: str, which: str) -> Plane:
    k = keep(PLANES[which](spark, d).where("units > 0"))
    r = k.agg(F.max("x").alias("x"), F.max("y").alias("y"), F.sum(F.col("units").cast("decimal(38,0)")).alias("w"), F.count("*").alias("n")).first()
    return Plane(k, int(r.x or 0) + 1, int(r.y or 0) + 1, int(r.w or 0), int(r.n))


def weight_cells(p: Plane, level: int, first_axis: int = 1, jitter: int | None = None, most: int = TREE_KEYS) -> list[tuple]:
    """(x_lo, x_hi, y_lo, y_hi) of the cells of one level of a kd tree over the plane, apart from any sampler's tree.

    The tree is built over the keys themselves while they are no more than `most`, else over that many drawn by a hash.
    """
    rows = p.keys if p.n <= most else p.keys.orderBy(F.xxhash64(F.lit("tree"), "hk")).limit(most)
    t = rows.select("x", "y", "units", "hk").orderBy("hk").toArrow()
    x, y, w = (np.asarray(t.column(c)) for c in ("x", "y", "units"))
    off = (lambda node: 0.35 + 0.3 * W._u("jitter", jitter, node)) if jitter else None
    tree, _ = kdtree.build([x, y], w.astype(np.float64), first_axis=first_axis, depth=level, jitter=off)
    return [(*b[0], *b[1]) for b in kdtree.leaf_boxes(tree, [0, 0], [p.wide, p.high]).values()]


def weight_boxes(cells: list[tuple], level: int, queries: int, rects: int, seed: int = 1) -> list[tuple]:
    """Boxes of queries that draw their cells by a hash, each once."""
    out = []
    for q in range(queries):
        order = sorted(range(len(cells)), key=lambda i: W._u("weight", seed, level, q, i))
        out += [(q, r, *map(int, cells[i])) for r, i in enumerate(order[:rects])]
    return out


def truth(p: Plane, boxes: DataFrame) -> DataFrame:
    """(query_id, exact) by the binned join."""
    return W.exact_boxes(p.keys, boxes, "x", "y", "units", max(1, p.wide // 64), max(1, p.high // 64))
