"""Measures of accuracy and cost."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangekeep.functions import UNIT
from rangekeep.sources.shared import small


def errors(answers: DataFrame, total: float) -> DataFrame:
    """From (est, exact) rows: abs_error and sse relative to the total, rel_error over queries with weight, and how many have none."""
    off = F.abs(F.col("est") - F.col("exact"))
    return answers.agg(
        F.avg(off / F.lit(float(total))).alias("abs_error"), F.sum(F.pow(off / F.lit(float(total)), F.lit(2.0))).alias("sse"),
        F.avg(F.when(F.col("exact") != 0, off / F.col("exact"))).alias("rel_error"), F.count_if(F.col("exact") == 0).alias("no_weight"), F.count("*").alias("queries"),
    )


def group_discrepancy(inc: DataFrame, chosen: DataFrame, by: list[str]) -> DataFrame:
    """(by..., n_sampled, mass, off): sampled keys of each group against its expected number."""
    rows = inc.join(chosen.select("hk").withColumn("__in", F.lit(1)), "hk", "left")
    return rows.groupBy(*by).agg(F.count("__in").alias("n_sampled"), (F.sum("ticks") / float(UNIT)).alias("mass")).withColumn("off", F.abs(F.col("n_sampled") - F.col("mass")))


def prefix_discrepancy(inc: DataFrame, chosen: DataFrame, order: list[str]) -> DataFrame:
    """One row: the largest deviation over prefixes and over intervals, from one running sum. For moderate key sets."""
    rows = inc.join(chosen.select("hk").withColumn("__in", F.lit(1)), "hk", "left")
    run = Window.orderBy(*order, "hk").rowsBetween(Window.unboundedPreceding, 0)
    dev = (F.sum(F.coalesce(F.col("__in"), F.lit(0)) * F.lit(UNIT) - F.col("ticks")).over(run) / float(UNIT)).alias("dev")
    return rows.select(dev).agg(
        F.max(F.abs("dev")).alias("prefix"), (F.greatest(F.max("dev"), F.lit(0.0)) - F.least(F.min("dev"), F.lit(0.0))).alias("interval")
    )


def error_bound(discrepancy: float, tau: float) -> float:
    """A range sum is off by no more than its count's deviation times the threshold."""
    return discrepancy * tau


def check_aggregate(samples: np.ndarray, p: np.ndarray, subsets: list[list[int]], z: float = 5.0) -> dict[str, bool]:
    """What replicates (rows of 0, 1 or undecided masses) of an aggregation must show: means p, a constant sum, and that
    keys of a subset are all in, or all out, no more often than independent draws would have it, within z deviations."""
    n = len(samples)
    near = lambda got, want: bool((got - want <= z * np.sqrt(np.maximum(want * (1 - want), 1e-12) / n) + 1e-12).all())
    joint = np.array([samples[:, s].prod(1).mean() for s in subsets]), np.array([p[s].prod() for s in subsets])
    none = np.array([(1 - samples[:, s]).prod(1).mean() for s in subsets]), np.array([(1 - p[s]).prod() for s in subsets])
    mean = samples.mean(0)
    return {
        "expectation": bool((np.abs(mean - p) <= z * np.sqrt(np.maximum(p * (1 - p), 1e-12) / n) + 1e-12).all()),
        "sum": bool(np.allclose(samples.sum(1), p.sum())), "inclusion": near(*joint), "exclusion": near(*none),
    }


def theory(s: int, d: int, mass: float) -> dict[str, float]:
    """Expected orders of deviation for a box of expected count mass: blind and aware samples, and cells a box can cut."""
    cut = 2 * d * s ** ((d - 1) / d)
    return {
        "oblivious": math.sqrt(mass), "oblivious_max": math.sqrt(s * math.log(s)) if s > 1 else 0.0,
        "aware": min(d * s ** ((d - 1) / (2 * d)), math.sqrt(mass)), "boundary": cut, "mu": min(mass, cut),
    }


def boundary_cells(cells: DataFrame, boxes: DataFrame) -> DataFrame:
    """(query_id, rect_id, cut): cells (x0, x1, y0, y1) that a box meets without holding them whole."""
    meets = (F.col("x0") < F.col("x_hi")) & (F.col("x_lo") < F.col("x1")) & (F.col("y0") < F.col("y_hi")) & (F.col("y_lo") < F.col("y1"))
    whole = (F.col("x0") >= F.col("x_lo")) & (F.col("x1") <= F.col("x_hi")) & (F.col("y0") >= F.col("y_lo")) & (F.col("y1") <= F.col("y_hi"))
    rows = cells.join(small(boxes), meets & ~whole)
    n = rows.groupBy("query_id", "rect_id").agg(F.count("*").alias("c"))
    return boxes.select("query_id", "rect_id").join(n, ["query_id", "rect_id"], "left").select("query_id", "rect_id", F.coalesce("c", F.lit(0)).alias("cut"))


def variance_report(replicates: DataFrame, by: list[str], value: str) -> DataFrame:
    """Mean and variance of a value over replicates, for each group."""
    return replicates.groupBy(*by).agg(F.avg(value).alias("mean"), F.var_samp(value).alias("variance"), F.count("*").alias("replicates"))


def size_spread(sizes: DataFrame) -> DataFrame:
    return sizes.agg(F.min("n").alias("least"), F.avg("n").alias("mean"), F.max("n").alias("most"), F.stddev_samp("n").alias("sd"))


def size_bytes(elements: int, axes: int = 2) -> int:
    """Bytes of a summary of so many elements, with four bytes for each coordinate and the weight."""
    return elements * 4 * (axes + 1)


def gain(aware: float, oblivious: float) -> float:
    return aware / oblivious if oblivious else math.nan
