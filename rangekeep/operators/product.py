"""Samples of products of axes: the uniform cube, and the kd hierarchy over all light keys."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rangekeep.functions import UNIT, uniform
from rangekeep.operators import kdtree, local
from rangekeep.operators.chain import settle
from rangekeep.operators.ipps import threshold, with_inclusion
from rangekeep.operators.structures import Summary, finish
from rangekeep.operators.twopass import Product
from rangekeep.operators.twopass import _values
from rangekeep.sources.shared import keep

#: Rows that a part may hold, which one task cuts further in memory; nodes are cut in Spark until none holds more.
PART_ROWS = 1 << 18
#: Levels cut in Spark at least, for parallel work, and at most: beyond them only keys that agree on all axes stay together.
LEAST_LEVELS, MOST_LEVELS = 3, 56


def sample_hypercube(spark: SparkSession, h: int, d: int, seed: int = 1, portable: bool = True) -> DataFrame:
    """(cell, x0...): a uniform point in each unit cell of the cube [0, h)^d."""
    cells = spark.range(h**d).withColumnRenamed("id", "cell")
    at = [(F.floor(F.col("cell") / h**i) % h).cast("bigint") for i in range(d)]
    return cells.select("cell", *[(at[i] + uniform("cube", seed, "cell", F.lit(str(i)), portable=portable)).alias(f"x{i}") for i in range(d)])


def _columns(axes: list) -> list[str]:
    return Product(axes).columns


def _line(axis):
    """An axis as one value that can be ordered: a hierarchy's own natural order is a line along which its nodes are stretches."""
    return F.col(axis) if isinstance(axis, str) else F.struct(*axis.columns)


def distributed_cuts(light: DataFrame, axes: list, deep: int, part_rows: int = PART_ROWS, least: int = LEAST_LEVELS) -> tuple[DataFrame, int]:
    """(light with a heap number `node`, levels cut): balanced cuts until no node holds more than part_rows keys.

    Masses are folded per (node, value) before the running sum; a level's cuts, one a node, are a small kept table that
    the keys are joined with. Nodes are at most as many as parts are needed, doubled while one is too large.
    """
    rows, level = light.withColumn("node", F.lit(1).cast("bigint")), 0
    while level < MOST_LEVELS:
        axis = axes[level % len(axes)]
        sums = rows.groupBy("node", _line(axis).alias("v")).agg(F.sum(F.col("ticks").cast("decimal(38,0)")).alias("m"), F.count("*").alias("n"))
        run = Window.partitionBy("node").orderBy("v")
        whole = Window.partitionBy("node")
        c = sums.select("node", "v", F.sum("m").over(run).alias("c"), F.sum("m").over(whole).alias("t"), F.sum("n").over(whole).alias("n"), F.lead("v").over(run).alias("next"))
        off = F.when(F.col("next").isNotNull(), F.struct(F.abs(2 * F.col("c") - F.col("t")).alias("off"), F.col("v").alias("v")))
        best = keep(c.groupBy("node").agg(F.min(off).alias("b"), F.max("n").alias("n")).select("node", F.col("b.v").alias("cut"), "n"))
        facts = best.agg(F.max("n").alias("most"), F.count("cut").alias("cuts"), F.count("*").alias("nodes")).first()
        if (facts.most or 0) <= part_rows and level >= min(deep, least):
            break
        if not facts.cuts and level >= len(axes):
            break
        few = F.broadcast(best) if facts.nodes <= 100_000 else best
        rows = rows.join(few.select("node", "cut"), "node", "left")
        over = F.coalesce(_line(axis) > F.col("cut"), F.lit(False))
        rows = rows.withColumn("node", F.col("node") * 2 + over.cast("bigint")).select(*light.columns, "node")
        level += 1
    return rows, level


def _part(axes: list, first_axis: int, depth: int | None, stage: str, seed: int):
    """Cuts a part further, to nodes of about one unit or by depth more levels, and settles its keys up to the part's root.

    Adds each key's way down as 0s and 1s, and its ticks after settling: a unit, none, or the rest of the undecided key.
    """

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("hk")
        node, ticks = t.column("node")[0].as_py(), t.column("ticks").to_numpy()
        shape = Product(axes, 1.0 if depth is None else None, first_axis)
        cols = [_values(t.column(c)) for c in shape.columns]
        tree, leaf = shape.grow(cols, ticks / UNIT, depth)
        way = [""] * len(tree.axis)
        for i, p in enumerate(tree.parent):
            if p >= 0:
                way[i] = way[p] + ("0" if tree.left[p] == i else "1")
        # rows come by key and numbers by tag, seed and part, so that a retried task draws the same
        rng = np.random.default_rng([zlib.crc32(stage.encode()), seed, node])
        after = np.zeros(len(ticks), np.int64)
        got, left, mass = local.settle_tree(leaf, ticks, np.array(tree.parent), np.array(tree.depth), lambda _, rows: rng.random(len(rows)), rest=True)
        after[got] = UNIT
        after[left] = mass
        return pa.table({"hk": t.column("hk"), "node": t.column("node"), "ticks": t.column("ticks"), "way": pa.array([way[i] for i in leaf], pa.string()), "after": after})

    return run


def product_parts(light: DataFrame, axes: list, deep: int, depth: int | None, stage: str, seed: int, part_rows: int = PART_ROWS) -> tuple[DataFrame, int]:
    """((hk, node, ticks, way, after) of light keys, level of node): parts cut in Spark, each cut on and settled in its own task."""
    rows, top = distributed_cuts(light, axes, deep, part_rows)
    run = _part(axes, top % len(axes), None if depth is None else max(0, depth - top), stage, seed)
    return keep(rows.groupBy("node").applyInArrow(run, "hk string, node long, ticks long, way string, after long")), top


def node_counts(parts: DataFrame, top: int, chosen: DataFrame) -> DataFrame:
    """(node, n_sampled, mass, off) of every node of every level; chosen has hk."""
    rows = parts.join(chosen.select("hk").withColumn("__in", F.lit(1)), "hk", "left")
    above = [F.shiftright("node", i).cast("string") for i in range(1, top + 1)]
    below = F.transform(F.sequence(F.lit(0), F.length("way")), lambda n: F.concat_ws("/", F.col("node").cast("string"), F.col("way").substr(F.lit(1), n)))
    rows = rows.select(F.explode(F.concat(F.array(*above).cast("array<string>"), below)).alias("at"), "__in", "ticks")
    sums = rows.groupBy("at").agg(F.count("__in").alias("n_sampled"), (F.sum("ticks") / float(UNIT)).alias("mass"))
    return sums.withColumn("off", F.abs(F.col("n_sampled") - F.col("mass")))


def sample_product(keys: DataFrame, s: int, axes: list, depth: int | None = None, stage: str = "kd", seed: int = 1) -> Summary:
    """The kd hierarchy over all light keys, cut until a node holds one unit of mass at most, or by depth levels; heavy keys apart.

    Axes are column names (ordered), Prefixes or Levels. The first levels are cut in Spark, along a hierarchy's natural
    order, the rest part by part. Nodes of the last level settle within, then undecided keys settle upwards, nearest
    relatives first. For full-data trees; the two-pass form needs no sort of the data.
    """
    return _product(keys, s, axes, depth, stage, seed)[0]


def _product(keys: DataFrame, s: int, axes: list, depth: int | None = None, stage: str = "kd", seed: int = 1, part_rows: int = PART_ROWS) -> tuple[Summary, DataFrame, int]:
    """sample_product() with the parts and their level, for counts of nodes."""
    th = threshold(keys, s)
    inc = with_inclusion(keys, th.tau)
    light = inc.where(~F.col("is_heavy") & (F.col("ticks") > 0)).select(*dict.fromkeys(["hk", "ticks", *_columns(axes)]))
    deep = max(1, (s - th.k).bit_length() - 1) if depth is None else depth
    parts, top = product_parts(light, axes, deep, depth, stage, seed, part_rows)
    names = [f"n{i}" for i in range(top, -1, -1)]
    rows = parts.where((F.col("after") > 0) & (F.col("after") < UNIT)).select("hk", F.col("after").alias("ticks"), "node")
    rows = keep(rows.withColumns({n: F.shiftright("node", i) for i, n in enumerate(names)}))
    # a part has one undecided key at most; a group carries its ancestors along, so that the next level can group by them
    levels = [(list(reversed(names[i:])), [] if i == 0 else [names[i - 1]]) for i in range(len(names))]
    chosen = settle(rows, levels, stage, seed).unionByName(parts.where(F.col("after") == UNIT).select("hk"))
    return finish(inc, chosen, th, seed, "product"), parts, top
