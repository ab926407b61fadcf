"""A summary for each period, drawn side by side: thresholds and chains are windows within the period."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangekeep.functions import UNIT, ticks
from rangekeep.operators.chain import chain


def summarize_by(keys: DataFrame, period: str, s: int, order: list[str], stage: str = "period", seed: int = 1) -> DataFrame:
    """(period, key columns, units, is_heavy, adj_weight): an order-aware sample of size s of every period.

    The s heaviest keys of each period decide its threshold; a period with no more than s keys keeps them all.
    """
    rows = keys.where("units > 0")
    whole = rows.groupBy(period).agg(F.sum(F.col("units").cast("decimal(38,0)")).alias("w"), F.count("*").alias("n"))
    fall = Window.partitionBy(period).orderBy(F.desc("units"), "hk")
    ranked = rows.select(period, "units", "hk", (F.row_number().over(fall) - 1).alias("k")).where(F.col("k") < s)
    ranked = ranked.withColumn("h", F.sum(F.col("units").cast("decimal(38,0)")).over(fall.rowsBetween(Window.unboundedPreceding, 0)) - F.col("units"))
    light = ranked.join(whole, period).where((F.col("n") > s) & (F.col("units") * (F.lit(s) - F.col("k")) < F.col("w") - F.col("h")))
    first = light.groupBy(period).agg(F.min(F.struct("k", "h", "w")).alias("m"))
    tau = first.select(period, ((F.col("m.w") - F.col("m.h")).cast("double") / (F.lit(s) - F.col("m.k"))).alias("tau"))
    p = F.when(F.coalesce("tau", F.lit(0.0)) > 0, F.least(F.lit(1.0), F.col("units") / F.col("tau"))).otherwise(1.0)
    inc = rows.join(tau, period, "left").withColumn("ticks", ticks(p)).withColumn("is_heavy", F.col("ticks") >= UNIT)
    got, left = chain(inc.where(~F.col("is_heavy") & (F.col("ticks") > 0)), [period], order, stage, seed)
    chosen = got.select(period, "hk").unionByName(left.where(F.col("ticks") * 2 >= UNIT).select(period, "hk"))
    out = inc.where("is_heavy").unionByName(inc.where(~F.col("is_heavy")).join(chosen, [period, "hk"], "left_semi").select(inc.columns))
    return out.withColumn("adj_weight", F.greatest(F.col("units").cast("double"), F.coalesce("tau", F.lit(0.0)))).drop("ticks", "tau")
