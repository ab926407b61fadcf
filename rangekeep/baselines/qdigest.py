"""q-digests: dyadic nodes with enough mass of their own; lighter ones hand theirs up."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rangekeep.sources.shared import keep

#: Levels between two written ones. Each level's nodes rest on all levels below, which are not computed again for each.
EVERY = 4
#: Points of a stretch of the outer axis, all of whose nodes one task makes in memory.
STRETCH_POINTS = 1 << 15


def build_1d(points: DataFrame, x: str, w: str, bits: int, share: float) -> DataFrame:
    """(level, k, units): siblings that hold less than share of all mass between them go to their parent."""
    total = int(points.agg(F.coalesce(F.sum(w), F.lit(0)).alias("t")).first().t)
    now, out = points.groupBy(F.col(x).alias("k")).agg(F.sum(w).alias("units")).where("units > 0"), None
    for level in range(bits):
        if level % EVERY == EVERY - 1:
            now = keep(now)
        up = now.groupBy(F.shiftright("k", 1).alias("p")).agg(F.sum("units").alias("both"))
        rows = now.withColumn("p", F.shiftright("k", 1)).join(up, "p")
        stay = rows.where(F.col("both") >= F.lit(share * total)).select(F.lit(level).alias("level"), "k", "units")
        out = stay if out is None else out.unionByName(stay)
        now = up.where(F.col("both") < F.lit(share * total)).select(F.col("p").alias("k"), F.col("both").alias("units"))
    root = now.select(F.lit(bits).alias("level"), "k", "units")
    return root if out is None else out.unionByName(root)


def schedule(bits_x: int, bits_y: int) -> list[tuple[int, int]]:
    """How far each axis is folded after each step: the longer axis first, then in turn."""
    out, kx, ky = [(0, 0)], 0, 0
    while kx < bits_x or ky < bits_y:
        if bits_x - kx >= bits_y - ky:
            kx += 1
        else:
            ky += 1
        out.append((kx, ky))
    return out


def build_2d(points: DataFrame, x: str, y: str, w: str, bits_x: int, bits_y: int, share: float, total: int | None = None) -> DataFrame:
    """(kx, ky, x, y, units): nodes [x 2^kx, ...) by [y 2^ky, ...) whose mass, less what lies in kept nodes below, is at least share of all.

    The root takes the rest, so there are at most 1 / share + 1 nodes.
    """
    if total is None:
        total = int(points.agg(F.coalesce(F.sum(w), F.lit(0)).alias("t")).first().t)
    steps = schedule(bits_x, bits_y)
    now, out, had = points.select(F.col(x).alias("x"), F.col(y).alias("y"), F.col(w).alias("units")), None, (0, 0)
    for kx, ky in steps:
        now = now.groupBy(F.shiftright("x", kx - had[0]).alias("x"), F.shiftright("y", ky - had[1]).alias("y")).agg(F.sum("units").alias("units")).where("units > 0")
        had = (kx, ky)
        last = (kx, ky) == steps[-1]
        if (kx + ky) % EVERY == EVERY - 1:
            now = keep(now)
        full = F.col("units") >= F.lit(share * total)
        stay = (now if last else now.where(full)).select(F.lit(kx).alias("kx"), F.lit(ky).alias("ky"), "x", "y", "units")
        out = stay if out is None else out.unionByName(stay)
        now = now.where(~full)
    return out


def build_2d_nested(points: DataFrame, x: str, y: str, w: str, bits_x: int, bits_y: int, share: float) -> DataFrame:
    """A digest over x each of whose nodes, on every level, owns a digest over y.

    Nodes of x no wider than a stretch of it are made by one task in memory from the points of the stretch, which are
    shuffled once; wider ones see a stretch as one value.
    """
    spark = points.sparkSession
    bounds = points.agg(F.coalesce(F.sum(w), F.lit(0)).alias("t"), F.coalesce(F.max(x), F.lit(0)).alias("x"), F.count("*").alias("n")).first()
    least = float(share * int(bounds.t))
    low = max(0, min(bits_x, ((int(bounds.x) + 1) // (int(bounds.n) // STRETCH_POINTS + 1)).bit_length() - 1))
    a = points.select(F.col(x).cast("bigint").alias("x"), F.col(y).cast("bigint").alias("y"), F.col(w).cast("bigint").alias("units"))
    a = a.withColumn("__at", F.shiftright("x", low))
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    # a number of its own: few bytes make much work, so these partitions are not to be merged
    out = a.repartition(tasks, "__at").groupBy("__at").applyInArrow(_stretch(low, bits_y, least), "kx int, ky int, x long, y long, units long")
    if low == bits_x:
        return out
    wider = a.groupBy(F.col("__at").alias("x"), "y").agg(F.sum("units").alias("units"))
    copies = wider.select(F.explode(F.sequence(F.lit(low + 1), F.lit(bits_x))).alias("kx"), "x", "y", "units")
    now = copies.groupBy("kx", F.call_function("shiftright", F.col("x"), F.col("kx") - low).alias("x"), "y").agg(F.sum("units").alias("units")).where("units > 0")
    for ky in range(bits_y + 1):
        if ky:
            now = now.groupBy("kx", "x", F.shiftright("y", 1).alias("y")).agg(F.sum("units").alias("units"))
        if ky % EVERY == EVERY - 1:
            now = keep(now)
        full = F.col("units") >= F.lit(least)
        stay = (now if ky == bits_y else now.where(full)).select("kx", F.lit(ky).alias("ky"), "x", "y", "units")
        out = out.unionByName(stay)
        now = now.where(~full)
    return out


def _stretch(low: int, bits_y: int, least: float):
    """Points (x, y, units) of one stretch of 2^low values of x -> the digests over y of all nodes of x up to the stretch itself."""

    def folded(x: np.ndarray, y: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Rows with the same (x, y) next to each other become one."""
        starts = np.flatnonzero(np.concatenate([[True], (x[1:] != x[:-1]) | (y[1:] != y[:-1])])) if len(x) else np.zeros(0, np.int64)
        return x[starts], y[starts], np.add.reduceat(v, starts) if len(x) else v

    def run(t: pa.Table) -> pa.Table:
        x, y, v = (t.column(n).to_numpy().astype(np.int64) for n in ("x", "y", "units"))
        if np.abs(v.astype(np.float64)).sum() >= 2.0**62:
            raise OverflowError("the weight of a stretch passes 62 bits")
        out = [(np.zeros(0, np.int32),) * 2 + (np.zeros(0, np.int64),) * 3]
        for kx in range(low + 1):
            x = x >> 1 if kx else x
            order = np.lexsort((y, x))
            x, y, v = folded(x[order], y[order], v[order])
            held = v > 0
            nx, ny, u = x[held], y[held], v[held]
            for ky in range(bits_y + 1):
                if ky:  # folding y leaves the order as it is
                    nx, ny, u = folded(nx, ny >> 1, u)
                stay = np.ones(len(u), bool) if ky == bits_y else u.astype(np.float64) >= least
                k = int(stay.sum())
                out.append((np.full(k, kx, np.int32), np.full(k, ky, np.int32), nx[stay], ny[stay], u[stay]))
                nx, ny, u = nx[~stay], ny[~stay], u[~stay]
        return pa.table({n: np.concatenate(c) for n, c in zip(("kx", "ky", "x", "y", "units"), zip(*out, strict=True), strict=True)})

    return run


def fit_share(points: DataFrame, x: str, y: str, w: str, bits_x: int, bits_y: int, nodes: int, rounds: int = 5) -> DataFrame:
    """A 2-d digest of at most so many nodes: the share is halved in between by bisection."""
    total = int(points.agg(F.coalesce(F.sum(w), F.lit(0)).alias("t")).first().t)
    lo, hi, best = 0.02 / nodes, 1.0 / max(1, nodes - 1), None
    for _ in range(rounds):
        mid = (lo * hi) ** 0.5
        got = keep(build_2d(points, x, y, w, bits_x, bits_y, mid, total))
        if got.count() <= nodes:
            best, hi = got, mid
        else:
            lo = mid
    return best if best is not None else build_2d(points, x, y, w, bits_x, bits_y, hi, total)


def _span(k: Column, fold: Column) -> tuple[Column, Column]:
    size = F.call_function("shiftleft", F.lit(1).cast("bigint"), fold)
    return k * size, (k + 1) * size


def query(nodes: DataFrame, boxes: DataFrame, partial: str = "share") -> DataFrame:
    """(query_id, est): whole nodes count; nodes cut by a box count by their share of area, not at all (lower) or whole (upper)."""
    x0, x1 = _span(F.col("x"), F.col("kx"))
    y0, y1 = _span(F.col("y"), F.col("ky"))
    ox, oy = F.least(F.col("x_hi"), x1) - F.greatest(F.col("x_lo"), x0), F.least(F.col("y_hi"), y1) - F.greatest(F.col("y_lo"), y0)
    part = (ox * oy).cast("double") / ((x1 - x0) * (y1 - y0)).cast("double")
    weight = {"share": part, "lower": F.when(part >= 1, 1.0).otherwise(0.0), "upper": F.lit(1.0)}[partial]
    rows = boxes.join(F.broadcast(nodes), (ox > 0) & (oy > 0))
    sums = rows.groupBy("query_id").agg(F.sum(F.col("units") * weight).alias("e"))
    return boxes.select("query_id").distinct().join(sums, "query_id", "left").select("query_id", F.coalesce("e", F.lit(0.0)).alias("est"))
