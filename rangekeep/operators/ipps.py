"""Inclusion probabilities proportional to size: the threshold for a sample size, and the split it makes."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangekeep.functions import UNIT, ticks, ticks_sql

#: Up to this size the heaviest keys are sorted; beyond it the threshold is found by repeated sums.
SORTED = 1_000_000


@dataclass(frozen=True)
class Threshold:
    """p = min(1, units / tau); k keys of total weight heavy have p = 1; tau = 0 keeps every key."""

    tau: float
    k: int
    heavy: int
    total: int
    n: int
    s: int


def totals(keys: DataFrame) -> tuple[int, int]:
    r = keys.where("units > 0").agg(F.coalesce(F.sum(F.col("units").cast("decimal(38,0)")), F.lit(0)).alias("w"), F.count("*").alias("n")).first()
    return int(r.w), int(r.n)


def threshold(keys: DataFrame, s: int, method: str = "auto") -> Threshold:
    """The tau for which the probabilities add up to s.

    Only the s heaviest keys can be heavy. Among them, in falling order, the light ones begin with the first whose
    weight lies under (W - H) / (s - k), where k keys of weight H stand before it.
    """
    if s < 1:
        raise ValueError("s is at least 1")
    w, n = totals(keys)
    if n <= s:
        return Threshold(0.0, n, w, w, n, s)
    if method == "iterate" or (method == "auto" and s > SORTED):
        return _iterate(keys, w, n, s)
    top = keys.where("units > 0").orderBy(F.desc("units")).limit(s)
    run = Window.orderBy(F.desc("units"), "i")
    ranked = top.withColumn("i", F.monotonically_increasing_id()).select(
        "units", (F.row_number().over(run) - 1).alias("k"), F.sum(F.col("units").cast("decimal(38,0)")).over(run.rowsBetween(Window.unboundedPreceding, 0)).alias("c")
    )
    h = (F.col("c") - F.col("units")).cast("decimal(38,0)")
    light = ranked.select("k", h.alias("h"), "units").where((F.col("units").cast("decimal(38,0)") * (F.lit(s) - F.col("k"))) < F.lit(w).cast("decimal(38,0)") - F.col("h"))
    first = light.agg(F.min(F.struct("k", "h")).alias("m")).first().m
    if first is None:
        # no room for a light key: as many ties as s at least
        return _iterate(keys, w, n, s)
    return Threshold((w - int(first.h)) / (s - first.k), int(first.k), int(first.h), w, n, s)


def _iterate(keys: DataFrame, w: int, n: int, s: int) -> Threshold:
    """Starts at W / s; heavy keys take their weight out, tau falls no more when no key is heavy anew."""
    tau, seen = w / s, -1
    while True:
        r = keys.where(F.col("units") >= F.lit(tau)).agg(F.count("*").alias("k"), F.coalesce(F.sum(F.col("units").cast("decimal(38,0)")), F.lit(0)).alias("h")).first()
        k, h = int(r.k), int(r.h)
        if k == seen or k >= s:
            return Threshold(tau, k, h, w, n, s)
        seen, tau = k, (w - h) / (s - k)


def local_threshold(weights: np.ndarray, total: float, s: int) -> float:
    """The same from an array that holds every key that can be heavy, and the total weight of all keys."""
    w = np.sort(np.asarray(weights, np.float64))[::-1][:s]
    before = np.concatenate([[0.0], np.cumsum(w)])[:-1]
    k = np.arange(len(w))
    light = np.flatnonzero(w * (s - k) < total - before)
    if not len(light):
        left = s - len(w)
        return (total - w.sum()) / left if left > 0 else 0.0
    return (total - before[light[0]]) / (s - k[light[0]])


def with_inclusion(keys: DataFrame, tau: float) -> DataFrame:
    """keys of positive weight with p, ticks and is_heavy."""
    rows = keys.where("units > 0")
    if tau <= 0:
        return rows.select("*", F.lit(1.0).alias("p"), F.lit(UNIT).cast("bigint").alias("ticks"), F.lit(True).alias("is_heavy"))
    p = F.least(F.lit(1.0), F.col("units") / F.lit(tau))
    return rows.withColumn("p", p).withColumn("ticks", ticks(F.col("p"))).withColumn("is_heavy", F.col("ticks") >= UNIT)


def threshold_sql(keys: str, s: int, name: str = "th") -> str:
    """CTEs ending in `name` (tau, k, heavy, total, n) over a CTE of keys."""
    return f"""
{name}_t AS (SELECT coalesce(sum(units), 0)::BIGINT AS w, count(*) AS n FROM {keys} WHERE units > 0),
{name}_r AS (SELECT units, row_number() OVER o - 1 AS k, sum(units) OVER (o ROWS UNBOUNDED PRECEDING) - units AS h FROM {keys} WHERE units > 0 WINDOW o AS (ORDER BY units DESC, hk)),
{name}_l AS (SELECT k, h FROM {name}_r, {name}_t WHERE n > {s} AND k < {s} AND units * ({s} - k) < w - h ORDER BY k LIMIT 1),
{name} AS (SELECT coalesce((SELECT (w - h)::DOUBLE / ({s} - k) FROM {name}_l), 0.0::DOUBLE) AS tau, coalesce((SELECT k FROM {name}_l), n)::BIGINT AS k,
  coalesce((SELECT h FROM {name}_l), w)::BIGINT AS heavy, w AS total, n::BIGINT AS n FROM {name}_t)"""


def inclusion_sql(keys: str, th: str = "th") -> str:
    """A SELECT of keys with p, ticks, is_heavy."""
    p = "CASE WHEN tau > 0 THEN least(1.0::DOUBLE, units / tau) ELSE 1.0::DOUBLE END"
    return f"SELECT *, ticks >= {UNIT} AS is_heavy FROM (SELECT {keys}.*, {p} AS p, {ticks_sql(p)} AS ticks FROM {keys}, {th} WHERE units > 0)"
