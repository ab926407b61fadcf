"""Settling probability masses along a sequence, as one window instead of a loop.

Items in order hand on one undecided key at a time. Its mass before an item is the running sum of ticks modulo one
unit, whatever the draws, so only its identity is random: an item of mass t that meets a mass q takes its place with
odds t : q while both fit in a unit; where they fill it, one of the two is sampled and the other keeps the rest. So
every draw is decided by the item's own columns, and the identity is the last item that took the place.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rangekeep.functions import UNIT, uniform, uniform_sql
from rangekeep.sources.shared import keep

#: Levels of a deep hierarchy settled in one plan: each level's rows are read twice, so longer plans are cut by a table.
PLAN_LEVELS = 4


def takes_place(q: Column, t: Column, u: Column) -> Column:
    total = q + t
    return u < F.when(total >= UNIT, (UNIT - t) / (2.0 * UNIT - total)).otherwise(t / total)


def chain(light: DataFrame, group: list[str], order: list[str], stage: str, seed: int = 1, start: Column | None = None) -> tuple[DataFrame, DataFrame]:
    """(sampled: hk), (leftover: group..., hk, ticks) of rows (group..., order..., hk, ticks) with 0 < ticks < UNIT.

    start, if given, is a mass that the group inherits from an undecided key outside; where that key is meant, hk is null.
    """
    q0 = F.lit(0) if start is None else start
    run = Window.partitionBy(*group).orderBy(*order, "hk")
    rows = light.withColumn("__cum", F.sum("ticks").over(run.rowsBetween(Window.unboundedPreceding, 0)) + q0)
    q = F.pmod(F.col("__cum") - F.col("ticks"), F.lit(UNIT))
    rows = rows.withColumn("__q", q).withColumn("__took", takes_place(F.col("__q"), F.col("ticks"), uniform(stage, seed, "hk")))
    took = F.when(F.col("__took"), F.col("hk"))
    rows = rows.withColumn("__prev", F.last(took, ignorenulls=True).over(run.rowsBetween(Window.unboundedPreceding, -1)))
    full = rows.where(F.col("__q") + F.col("ticks") >= UNIT)
    sampled = full.select(*group, F.when(F.col("__took"), F.col("__prev")).otherwise(F.col("hk")).alias("hk"))
    # the last taker of a group: the largest place in its order among those that took
    last = rows.groupBy(*group).agg(
        F.max_by("hk", F.when(F.col("__took"), F.struct(*order, "hk"))).alias("hk"), F.pmod(F.max("__cum"), F.lit(UNIT)).alias("ticks")
    )
    return sampled, last.where("ticks > 0")


def settle(light: DataFrame, levels: list[tuple[list[str], list[str]]], stage: str, seed: int = 1) -> DataFrame:
    """(hk) of the sampled keys: chains level by level, (group columns, order columns) from the finest to the root.

    What is undecided in the groups of one level is the input of the next; the last group list should be empty. The
    mass left at the end differs from a whole number only by rounding and goes to the nearer one.
    """
    rows = light.where((F.col("ticks") > 0) & (F.col("ticks") < UNIT))
    out = None
    for i, (group, order) in enumerate(levels):
        if i and i % PLAN_LEVELS == 0 and len(levels) > PLAN_LEVELS + 1:
            rows = keep(rows)
        got, rows = chain(rows, group, order, f"{stage}{i}", seed)
        got = got.select("hk")
        out = got if out is None else out.unionByName(got)
    return out.unionByName(rows.where(F.col("ticks") * 2 >= UNIT).select("hk"))


def settle_sql(light: str, levels: list[tuple[list[str], list[str]]], stage: str, seed: int = 1, name: str = "st") -> str:
    """DuckDB's form of settle(): CTEs ending in `name` (hk)."""
    parts, src, got = [], f"(SELECT * FROM {light} WHERE ticks > 0 AND ticks < {UNIT})", []
    for i, (group, order) in enumerate(levels):
        part = f"PARTITION BY {', '.join(group)} " if group else ""
        ord_ = ", ".join([*order, "hk"])
        cols = "".join(f"{c}, " for c in dict.fromkeys([*group, *order]))
        g = "".join(f"{c}, " for c in group)
        place = f"ROW({', '.join([*order, 'hk'])})" if order else "ROW(hk)"
        parts += [
            f"{name}{i}a AS (SELECT {cols}hk, ticks, sum(ticks) OVER ({part}ORDER BY {ord_} ROWS UNBOUNDED PRECEDING)::BIGINT AS cum, {uniform_sql(f'{stage}{i}', seed, 'hk')} AS u FROM {src})",
            f"{name}{i}b AS (SELECT *, (cum - ticks) % {UNIT} AS q FROM {name}{i}a)",
            f"{name}{i}c AS (SELECT *, u < CASE WHEN q + ticks >= {UNIT} THEN ({UNIT} - ticks)::DOUBLE / ({2 * UNIT}.0::DOUBLE - (q + ticks)) ELSE ticks::DOUBLE / (q + ticks) END AS took FROM {name}{i}b)",
            f"{name}{i}d AS (SELECT *, last_value(CASE WHEN took THEN hk END IGNORE NULLS) OVER ({part}ORDER BY {ord_} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prev FROM {name}{i}c)",
            f"{name}{i}s AS (SELECT CASE WHEN took THEN prev ELSE hk END AS hk FROM {name}{i}d WHERE q + ticks >= {UNIT})",
            f"{name}{i}l AS (SELECT * FROM (SELECT {g}max_by(hk, {place}) FILTER (took) AS hk, max(cum) % {UNIT} AS ticks FROM {name}{i}d{f' GROUP BY {', '.join(group)}' if group else ''}) WHERE ticks > 0)",
        ]
        src = f"{name}{i}l"
        got.append(f"SELECT hk FROM {name}{i}s")
    got.append(f"SELECT hk FROM {src} WHERE ticks * 2 >= {UNIT}")
    parts.append(f"{name} AS ({' UNION ALL '.join(got)})")
    return ",\n".join(parts)
