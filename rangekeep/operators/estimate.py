"""Estimates from a summary: sums over any subset, bounds, quantiles, heavy hitters, trends, boxes, merges."""

from __future__ import annotations

import math
from decimal import Decimal

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rangekeep.operators.ipps import Threshold
from rangekeep.operators.structures import Summary, varopt
from rangekeep.sources.shared import small


def estimate(summary: Summary, predicate: Column | str | None = None) -> DataFrame:
    """One row: est, the sum of adjusted weights, and n_keys, how many sampled keys it rests on."""
    rows = summary.rows if predicate is None else summary.rows.where(predicate)
    return rows.agg(F.coalesce(F.sum("adj_weight"), F.lit(0.0)).alias("est"), F.count("*").alias("n_keys"))


def reaches(th: Threshold) -> Column:
    """Whether a row's units reach the threshold, in whole numbers. is_heavy says so of shares rounded to ticks, and once the
    threshold passes 2^41 a share that lacks a whole unit of weight rounds to 1."""
    if th.k >= th.n:
        return F.lit(True)
    return F.col("units").cast("decimal(20,0)") * F.lit(th.s - th.k).cast("decimal(18,0)") >= F.lit(str(th.total - th.heavy)).cast("decimal(38,0)")


def whole_total(th: Threshold | None = None) -> Column:
    """The sum of adjusted weights to the next whole unit. Decimals add exactly in any order; as doubles, thousands of weights
    whose sum nears 2^47 drift by whole units.

    With the threshold that the rows were drawn at, no double takes part: keys that reach it count their units, and each other
    one its share of the light weight, so that totals beyond 2^53 are whole too.
    """
    if th is None:
        return F.round(F.sum(F.col("adj_weight").cast("decimal(38,9)")), 0).cast("bigint")
    heavy = F.coalesce(F.sum(F.when(reaches(th), F.col("units").cast("decimal(38,0)"))), F.lit(0).cast("decimal(38,0)"))
    if th.k >= th.n:
        return heavy.cast("bigint")
    shares = 2 * (th.s - th.k)
    light = F.count_if(~reaches(th)).cast("decimal(20,0)") * F.lit(str(2 * (th.total - th.heavy))).cast("decimal(38,0)")
    half = F.lit(shares // 2).cast("decimal(38,0)")
    return (heavy + F.call_function("div", light + half, F.lit(shares).cast("decimal(38,0)"))).cast("bigint")


def count_bounds(x: np.ndarray, delta: float) -> tuple[np.ndarray, np.ndarray]:
    """Interval of means mu for which a count x is not unlikely: exp(x - mu) (mu / x)^x >= delta / 2 on either side."""
    x = np.asarray(x, float)
    floor = math.log(delta / 2)

    def log_tail(mu):
        with np.errstate(divide="ignore", invalid="ignore"):
            return np.where(x > 0, x - mu + x * np.log(np.where(x > 0, mu / np.where(x > 0, x, 1), 1)), -mu)

    lo_a, lo_b = np.zeros_like(x), x.copy()
    hi_a, hi_b = x.copy(), x + 4 * (np.sqrt(x + 1) + 1) * (1 - floor)
    for _ in range(80):
        m = (lo_a + lo_b) / 2
        ok = log_tail(m) >= floor
        lo_b, lo_a = np.where(ok, m, lo_b), np.where(ok, lo_a, m)
        m = (hi_a + hi_b) / 2
        ok = log_tail(m) >= floor
        hi_a, hi_b = np.where(ok, m, hi_a), np.where(ok, hi_b, m)
    return np.where(x > 0, lo_b, 0.0), hi_a


def with_bounds(counts: DataFrame, tau: float, conf: float = 0.95) -> DataFrame:
    """counts (heavy_sum, n_light, ...) with est, lo and hi: the heavy part is exact, the light count is bounded."""

    @F.pandas_udf("lo double, hi double")
    def bounds(n: pd.Series) -> pd.DataFrame:
        lo, hi = count_bounds(n.to_numpy(), 1 - conf)
        return pd.DataFrame({"lo": lo, "hi": hi})

    rows = counts.withColumn("__b", bounds(F.col("n_light")))
    return rows.select(
        *counts.columns, (F.col("heavy_sum") + F.col("n_light") * tau).alias("est"), (F.col("heavy_sum") + F.col("__b.lo") * tau).alias("lo"), (F.col("heavy_sum") + F.col("__b.hi") * tau).alias("hi")
    )


def split_counts(summary: Summary, *by: str) -> DataFrame:
    heavy = F.coalesce(F.sum(F.when(F.col("is_heavy"), F.col("units").cast("double"))), F.lit(0.0)).alias("heavy_sum")
    return summary.rows.groupBy(*by).agg(heavy, F.count_if(~F.col("is_heavy")).alias("n_light"))


def est_quantile(summary: Summary, column: str, qs: list[float]) -> DataFrame:
    """Weighted quantiles: the least value at which the running adjusted weight reaches q of the whole.

    Light keys weigh the same, so that a running sum often equals q of the whole; decimals see that, doubles by chance.
    """
    run, w = Window.orderBy(column, "hk"), F.col("adj_weight").cast("decimal(28,9)")
    rows = summary.rows.select(column, "hk", w.alias("w")).withColumn("c", F.sum("w").over(run.rowsBetween(Window.unboundedPreceding, 0)).cast("decimal(30,9)"))
    rows = rows.withColumn("t", F.sum("w").over(Window.partitionBy()).cast("decimal(30,9)"))
    bounds = [F.struct(F.lit(float(q)).alias("q"), (F.col("t") * F.lit(Decimal(str(q))).cast("decimal(18,17)")).alias("b")) for q in qs]
    rows = rows.select(column, "c", F.explode(F.array(*bounds)).alias("at"))
    return rows.where(F.col("c") >= F.col("at.b") - F.lit(Decimal("0.000001"))).groupBy(F.col("at.q").alias("q")).agg(F.min(column).alias("value"))


def est_heavy_hitters(summary: Summary, by: list[str], phi: float) -> DataFrame:
    sums = summary.rows.groupBy(*by).agg(F.sum("adj_weight").alias("est"))
    return sums.where(F.col("est") >= F.lit(phi * summary.th.total))


def est_trend(sums: DataFrame, period: str, value: str = "est") -> DataFrame:
    """Change of each period's estimate against the one before."""
    return sums.withColumn("change", F.col(value) - F.lag(value).over(Window.orderBy(period)))


def est_corr(rows: DataFrame, x: str, y: str, w: str = "adj_weight") -> DataFrame:
    """Weighted correlation of two numbers."""
    a, b, c = F.col(x).cast("double"), F.col(y).cast("double"), F.col(w)
    m = rows.agg(F.sum(c).alias("n"), F.sum(a * c).alias("sx"), F.sum(b * c).alias("sy"), F.sum(a * a * c).alias("sxx"), F.sum(b * b * c).alias("syy"), F.sum(a * b * c).alias("sxy"))
    top = F.col("n") * F.col("sxy") - F.col("sx") * F.col("sy")
    return m.select((top / F.sqrt((F.col("n") * F.col("sxx") - F.col("sx") * F.col("sx")) * (F.col("n") * F.col("syy") - F.col("sy") * F.col("sy")))).alias("corr"))


def representatives(summary: Summary, predicate: Column | str, k: int) -> DataFrame:
    return summary.rows.where(predicate).orderBy(F.desc("adj_weight"), "hk").limit(k)


def in_boxes(points: DataFrame, boxes: DataFrame, x: str, y: str) -> DataFrame:
    """Points with the boxes (query_id, rect_id, x_lo, x_hi, y_lo, y_hi; half open) that hold them; boxes are a workload's few thousand rows."""
    hit = (F.col(x) >= F.col("x_lo")) & (F.col(x) < F.col("x_hi")) & (F.col(y) >= F.col("y_lo")) & (F.col(y) < F.col("y_hi"))
    return points.join(small(boxes), hit)


def estimate_boxes(summary: Summary, boxes: DataFrame, x: str, y: str) -> DataFrame:
    """(query_id, est) for every query, zero where no sampled key falls in."""
    sums = in_boxes(summary.rows, boxes, x, y).groupBy("query_id").agg(F.sum("adj_weight").alias("e"))
    return boxes.select("query_id").distinct().join(sums, "query_id", "left").select("query_id", F.coalesce("e", F.lit(0.0)).alias("est"))


def union_estimate(parts: list[Summary], predicate: Column | str | None = None) -> DataFrame:
    """One row: the sum of several summaries' estimates; their errors are independent, so they add like square roots."""
    rows = None
    for p in parts:
        e = estimate(p, predicate)
        rows = e if rows is None else rows.unionByName(e)
    return rows.agg(F.sum("est").alias("est"), F.sum("n_keys").alias("n_keys"))


def merge(parts: list[Summary], s: int, sampler=varopt, **how) -> Summary:
    """One summary of size s from several over disjoint key sets: their adjusted weights are sampled again."""
    rows = None
    for p in parts:
        r = p.rows.select(*[c for c in p.rows.columns if c not in ("units", "p", "is_heavy", "adj_weight")], F.floor(F.col("adj_weight") + 0.5).cast("bigint").alias("units"))
        rows = r if rows is None else rows.unionByName(r, allowMissingColumns=True)
    return sampler(rows, s, **how)


