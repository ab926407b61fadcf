"""Range-aware samples of disjoint ranges, hierarchies and orders, and the samples that ignore structure."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangekeep.functions import UNIT, uniform
from rangekeep.operators.chain import settle, takes_place
from rangekeep.operators.ipps import Threshold, threshold, with_inclusion
from rangekeep.sources.shared import keep, small

#: Groups of two hex digits of the key's hash: a window each, so that no task chains all keys.
BUCKETS = 256


@dataclass(frozen=True)
class Summary:
    """A sample: its keys with weight in units and adjusted weight, and the threshold it was drawn at."""

    rows: DataFrame
    th: Threshold
    seed: int
    structure: str


def finish(inc: DataFrame, chosen: DataFrame, th: Threshold, seed: int, structure: str) -> Summary:
    """Heavy keys and the chosen light ones, each standing for max(units, tau)."""
    heavy = inc.where("is_heavy")
    # at most s keys are chosen, so this side is small by construction
    light = inc.where(~F.col("is_heavy")).join(F.broadcast(chosen) if th.s <= 1_000_000 else chosen, "hk", "left_semi")
    rows = heavy.unionByName(light).withColumn("adj_weight", F.greatest(F.col("units").cast("double"), F.lit(th.tau))).drop("ticks")
    return Summary(rows, th, seed, structure)


def _aware(keys: DataFrame, s: int, levels: list[tuple[list[str], list[str]]], stage: str, seed: int, structure: str) -> Summary:
    th = threshold(keys, s)
    inc = with_inclusion(keys, th.tau)
    cols = list(dict.fromkeys(["hk", "ticks", *[c for g, o in levels for c in [*g, *o]]]))
    chosen = settle(inc.where(~F.col("is_heavy")).select(*cols), levels, stage, seed)
    return finish(inc, chosen, th, seed, structure)


def levels_disjoint(range_cols: list[str]) -> list[tuple[list[str], list[str]]]:
    return [(range_cols, []), ([], range_cols)]


def levels_hierarchy(path: list[str]) -> list[tuple[list[str], list[str]]]:
    """From the finest nodes to the root; a group's items are its children, in order."""
    return [(path[:d], [path[d]] if d < len(path) else []) for d in range(len(path), -1, -1)]


def sample_disjoint(keys: DataFrame, s: int, range_cols: list[str], stage: str = "disjoint", seed: int = 1) -> Summary:
    """Every range gets the floor or the ceiling of its mass: ranges settle within themselves first."""
    return _aware(keys, s, levels_disjoint(range_cols), stage, seed, "disjoint")


def sample_hierarchy(keys: DataFrame, s: int, path: list[str], stage: str = "hier", seed: int = 1) -> Summary:
    """path from coarse to fine, keys below the last: every node gets the floor or the ceiling of its mass."""
    return _aware(keys, s, levels_hierarchy(path), stage, seed, "hierarchy")


def with_path_levels(keys: DataFrame, path: str, depth: int | None = None) -> tuple[DataFrame, list[str]]:
    """Columns l1..ldepth of prefixes of an array path, null below a path's end: a leaf right under a high node waits there.

    depth defaults to the longest path of the keys.
    """
    depth = (keys.agg(F.max(F.size(path))).first()[0] or 0) if depth is None else depth
    cols = [f"l{i}" for i in range(1, depth + 1)]
    return keys.withColumns({c: F.when(F.size(path) >= i, F.get(path, F.lit(i - 1))) for i, c in enumerate(cols, 1)}), cols


def with_prefix_levels(keys: DataFrame, code: str, bits: int, steps: list[int]) -> tuple[DataFrame, list[str]]:
    """Columns of the leading bits of an integer code, for a binary prefix hierarchy cut at the given lengths."""
    cols = [f"b{n}" for n in steps]
    return keys.withColumns({c: F.shiftright(F.col(code), bits - n) for c, n in zip(cols, steps, strict=True)}), cols


def prefix_lengths(keys: DataFrame, code: str, bits: int) -> list[int]:
    """All prefix lengths, from one bit on, at which some node holds two keys. Where a prefix is shared its own prefixes are too, so the longest is searched by halves."""
    low, high = 0, bits
    while low < high:
        n = (low + high + 1) // 2
        shared = keys.groupBy(F.shiftright(F.col(code), bits - n)).count().where("count > 1")
        low, high = (n, high) if shared.limit(1).count() else (low, n - 1)
    return list(range(1, low + 1))


def sample_order(keys: DataFrame, s: int, order: list[str], stage: str = "order", seed: int = 1) -> Summary:
    """Left to right in one window: prefixes are off by less than 1, intervals by less than 2. For moderate key sets."""
    return _aware(keys, s, [([], order)], stage, seed, "order")


def sample_order_bucketed(keys: DataFrame, s: int, order: list[str], bucket: str, stage: str = "order", seed: int = 1) -> Summary:
    """The very sample of sample_order(), with a window for each bucket only.

    bucket is a column that rises with the order. Its masses, summed, say what undecided mass each bucket inherits;
    where a bucket's first items meet that inherited key, the key is named afterwards from the buckets before it.
    """
    th = threshold(keys, s)
    inc = with_inclusion(keys, th.tau)
    light = inc.where(~F.col("is_heavy") & (F.col("ticks") > 0)).select("hk", "ticks", bucket, *[c for c in order if c != bucket])
    before = Window.orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)  # a row for each bucket
    mass = light.groupBy(bucket).agg(F.sum("ticks").alias("m")).withColumn("__start", F.pmod(F.coalesce(F.sum("m").over(before), F.lit(0)), F.lit(UNIT))).drop("m")
    mass = keep(mass)
    rows = light.join(small(mass), bucket)
    stage0 = f"{stage}0"
    run = Window.partitionBy(bucket).orderBy(*order, "hk")
    rows = rows.withColumn("__cum", F.sum("ticks").over(run.rowsBetween(Window.unboundedPreceding, 0)) + F.col("__start"))
    rows = rows.withColumn("__q", F.pmod(F.col("__cum") - F.col("ticks"), F.lit(UNIT)))
    rows = rows.withColumn("__took", takes_place(F.col("__q"), F.col("ticks"), uniform(stage0, seed, "hk")))
    rows = rows.withColumn("__prev", F.last(F.when(F.col("__took"), F.col("hk")), ignorenulls=True).over(run.rowsBetween(Window.unboundedPreceding, -1)))
    full = rows.where(F.col("__q") + F.col("ticks") >= UNIT)
    got = full.select(bucket, F.when(F.col("__took"), F.col("__prev")).otherwise(F.col("hk")).alias("hk"))
    last = keep(rows.groupBy(bucket).agg(F.max_by("hk", F.when(F.col("__took"), F.struct(*order, "hk"))).alias("taker"), F.max("__cum").alias("cum")))
    named = last.select(bucket, F.last("taker", ignorenulls=True).over(before).alias("inherited"))
    got = got.join(small(named), bucket).select(F.coalesce("hk", "inherited").alias("hk"))
    end = last.agg(F.max_by("taker", F.when(F.col("taker").isNotNull(), F.col(bucket))).alias("hk"), F.max_by("cum", bucket).alias("c"))
    end = end.where(F.pmod(F.col("c"), F.lit(UNIT)) * 2 >= UNIT).select("hk")
    return finish(inc, got.unionByName(end), th, seed, "order")


def poisson(keys: DataFrame, s: int, stage: str = "poisson", seed: int = 1) -> Summary:
    """Independent draws; s keys in the mean."""
    th = threshold(keys, s)
    inc = with_inclusion(keys, th.tau)
    rows = inc.where(F.col("is_heavy") | (uniform(stage, seed, "hk") < F.col("p")))
    return Summary(rows.withColumn("adj_weight", F.greatest(F.col("units").cast("double"), F.lit(th.tau))).drop("ticks"), th, seed, "poisson")


def hash_bucket():
    return F.substring(F.md5(F.concat(F.lit("b|"), F.col("hk"))), 1, 2)


def varopt(keys: DataFrame, s: int, stage: str = "varopt", seed: int = 1) -> Summary:
    """Exactly s keys, blind to structure: keys meet in the order of a hash, within groups of the hash first."""
    mixed = keys.withColumn("hb", hash_bucket()).withColumn("ho", F.md5(F.col("hk")))
    out = _aware(mixed, s, [(["hb"], ["ho"]), ([], ["hb"])], stage, seed, "varopt")
    return Summary(out.rows.drop("hb", "ho"), out.th, seed, "varopt")


def reservoir(keys: DataFrame, s: int, stage: str = "reservoir", seed: int = 1) -> DataFrame:
    """s keys, all equally likely: those first by a hash."""
    return keys.withColumn("u", uniform(stage, seed, "hk")).orderBy("u", "hk").limit(s)


def systematic(keys: DataFrame, s: int, order: list[str], offset: float = 0.5) -> Summary:
    """One offset for all draws: low discrepancy, but pairs are not drawn as the aggregation's bounds ask. For contrast, on moderate sets."""
    th = threshold(keys, s)
    inc = with_inclusion(keys, th.tau)
    run = Window.orderBy(*order, "hk").rowsBetween(Window.unboundedPreceding, 0)
    shift = int(offset * UNIT)
    light = inc.where(~F.col("is_heavy")).withColumn("__c", F.sum("ticks").over(run) + shift)
    hit = light.where(F.floor(F.col("__c") / UNIT) > F.floor((F.col("__c") - F.col("ticks")) / UNIT))
    return finish(inc, hit.select("hk"), th, 0, "systematic")
