"""Count-sketches over dyadic rectangles: a sketch for each pair of levels, boxes from their dyadic covers."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rangekeep.baselines.dyadic import pieces
from rangekeep.functions import uniform, vectors
from rangekeep.sources.shared import keep, small

#: Log2 of the sides of a block of points that one task folds in memory.
BLOCK_X, BLOCK_Y = 9, 10


def width(s: int, rows: int, bits_x: int, bits_y: int) -> int:
    return max(1, s // (rows * (bits_x + 1) * (bits_y + 1)))


def _place(seed: int, wide: int, portable: bool) -> tuple[Column, Column]:
    at = ("lx", "ly", "row", "kx", "ky")
    bucket = F.floor(uniform("bucket", seed, *at, portable=portable) * wide).cast("bigint")
    sign = F.when(uniform("sign", seed, *at, portable=portable) < 0.5, 1).otherwise(-1).cast("bigint")
    return bucket, sign


def _fold(x: np.ndarray, y: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows with the same (x, y) next to each other become one."""
    starts = np.flatnonzero(np.concatenate([[True], (x[1:] != x[:-1]) | (y[1:] != y[:-1])]))
    return x[starts], y[starts], np.add.reduceat(w, starts)


#: Rectangles of a block that are hashed at a time.
AT_ONCE = 1 << 18


def _portable(seed: int):
    """Bucket and sign of rectangles as _place() has them, by md5: texts of the same shape are hashed together."""

    def run(wide: int, row: int, lx: np.ndarray, ly: np.ndarray, kx: np.ndarray, ky: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        shape = [vectors.digits(v) for v in (lx, ly, kx, ky)]
        code = ((shape[0] * 4 + shape[1]) * 32 + shape[2]) * 32 + shape[3]
        order = np.argsort(code, kind="stable")
        ends = np.flatnonzero(np.diff(code[order])) + 1
        bucket, sign = np.zeros(len(lx), np.int64), np.empty(len(lx), np.int64)
        for at in np.split(order, ends):
            a, b, c, d = (int(v[at[0]]) for v in shape)
            row_ = str(row).encode()
            number = lambda tag: vectors.md5_numbers([f"{tag}|{seed}".encode(), lx[at], ly[at], row_, kx[at], ky[at]], [0, a, b, 0, c, d])  # noqa: E731, B023
            if wide > 1:
                bucket[at] = np.floor(number("bucket") / float(1 << 52) * wide).astype(np.int64)
            sign[at] = np.where(number("sign") / float(1 << 52) < 0.5, 1, -1)
        return bucket, sign

    return run


def _quick(bucket_seed: int, sign_seed: int):
    """The same by xxhash64; the seeds are the hashes of tag and seed."""

    def run(wide: int, row: int, lx: np.ndarray, ly: np.ndarray, kx: np.ndarray, ky: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        def number(h: int) -> np.ndarray:
            h = np.full(len(lx), h % 2**64, np.uint64)
            for v in (lx, ly, np.full(len(lx), row)):
                h = vectors.xx_int(v.astype(np.uint64), h)
            for v in (kx, ky):
                h = vectors.xx_long(v.astype(np.uint64), h)
            return (h >> np.uint64(11)).astype(np.float64) / float(1 << 53)

        bucket = np.floor(number(bucket_seed) * wide).astype(np.int64) if wide > 1 else np.zeros(len(lx), np.int64)
        return bucket, np.where(number(sign_seed) < 0.5, 1, -1)

    return run


def _counted(levels: dict[int, set[int]], rows: int, wide: int, place):
    """Points (x, y, w) of one block -> (lx, ly, row, bucket, v): what the block adds to each counter of the levels."""

    def run(t: pa.Table) -> pa.Table:
        x, y, w = (t.column(n).to_numpy().astype(np.int64) for n in ("x", "y", "w"))
        if np.abs(w.astype(np.float64)).sum() >= 2.0**62:
            raise OverflowError("the weight of a block passes 62 bits")
        held, waiting, out = 0, [], [(np.zeros(0, np.int64),) * 5]

        def hashed() -> None:
            """The waiting rectangles join the counters: those of one counter are summed."""
            lx, ly, kx, ky, v = (np.concatenate(c) for c in zip(*waiting, strict=True))
            waiting.clear()
            for row in range(rows):
                bucket, sign = place(wide, row, lx, ly, kx, ky)
                order = np.lexsort((bucket, ly, lx))
                at = [c[order] for c in (lx, ly, bucket)]
                starts = np.flatnonzero(np.concatenate([[True], (at[0][1:] != at[0][:-1]) | (at[1][1:] != at[1][:-1]) | (at[2][1:] != at[2][:-1])]))
                sums = np.add.reduceat((v * sign)[order], starts)
                out.append((at[0][starts], at[1][starts], np.full(len(starts), row), at[2][starts], sums))

        for lx in range(max(levels) + 1):
            x = x >> 1 if lx else x
            order = np.lexsort((y, x))
            x, y, w = _fold(x[order], y[order], w[order])
            kx, ky, v = x, y, w
            wanted = levels.get(lx, ())
            for ly in range(max(wanted, default=-1) + 1):
                if ly:  # folding y leaves the order as it is
                    kx, ky, v = _fold(kx, ky >> 1, v)
                if ly in wanted:
                    waiting.append((np.full(len(v), lx), np.full(len(v), ly), kx, ky, v))
                    held += len(v)
                    if held >= AT_ONCE:
                        hashed()
                        held = 0
        if waiting:
            hashed()
        cols = [np.concatenate(c) for c in zip(*out, strict=True)]
        kinds = (np.int32, np.int32, np.int32, np.int64, np.int64)
        return pa.table({n: c.astype(k) for n, c, k in zip(("lx", "ly", "row", "bucket", "v"), cols, kinds, strict=True)})

    return run


def _asked(boxes: DataFrame, bits_x: int, bits_y: int, s: int, rows: int, seed: int, portable: bool) -> DataFrame:
    """The dyadic rectangles of boxes with their row, bucket and sign."""
    p = pieces(boxes, bits_x, bits_y).withColumn("row", F.explode(F.sequence(F.lit(0), F.lit(rows - 1))))
    bucket, sign = _place(seed, width(s, rows, bits_x, bits_y), portable)
    return p.withColumns({"bucket": bucket, "sign": sign})


def build(
    points: DataFrame, x: str, y: str, w: str, bits_x: int, bits_y: int, s: int, rows: int = 3, seed: int = 1, portable: bool = True, boxes: DataFrame | None = None
) -> DataFrame:
    """(lx, ly, row, bucket, counter): rectangles are folded and hashed in a task's memory, and only counters leave it. With boxes, the counters that their
    rectangles meet and no others.

    Counters add up, so points are cut into blocks, each folded by one task in memory, and rectangles wider than a block
    come in parts. Points are shuffled once (a key may come in several rows), rectangles never.
    """
    spark = points.sparkSession
    levels, met = {n: set(range(bits_y + 1)) for n in range(bits_x + 1)}, None
    if boxes is not None:
        met = keep(_asked(boxes, bits_x, bits_y, s, rows, seed, portable).select("lx", "ly", "row", "bucket").distinct())
        levels = {}
        for r in met.select("lx", "ly").distinct().collect():  # pairs of levels
            levels.setdefault(r.lx, set()).add(r.ly)
    a = points.select(F.col(x).cast("bigint").alias("x"), F.col(y).cast("bigint").alias("y"), F.col(w).cast("bigint").alias("w"))
    if not levels:
        a, levels = a.limit(0), {0: {0}}
    at = {"__bx": F.shiftright("x", BLOCK_X), "__by": F.shiftright("y", BLOCK_Y)}
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    # a number of its own: few bytes make much work, so these partitions are not to be merged
    blocks = a.withColumns(at).repartition(tasks, *at).groupBy(*at)
    wide = width(s, rows, bits_x, bits_y)
    if portable:
        place = _portable(seed)
    else:
        start = lambda tag: F.xxhash64(F.lit(tag), F.lit(seed)).alias(tag)
        place = _quick(*spark.range(1).select(start("bucket"), start("sign")).first())
    b = blocks.applyInArrow(_counted(levels, rows, wide, place), "lx int, ly int, row int, bucket long, v long")
    if met is not None:
        b = b.join(small(met), ["lx", "ly", "row", "bucket"], "left_semi")
    return b.groupBy("lx", "ly", "row", "bucket").agg(F.sum("v").alias("counter"))


def query(counters: DataFrame, boxes: DataFrame, bits_x: int, bits_y: int, s: int, rows: int = 3, seed: int = 1, portable: bool = True) -> DataFrame:
    """(query_id, est): the median over rows for each dyadic rectangle, summed."""
    p = _asked(boxes, bits_x, bits_y, s, rows, seed, portable).join(counters, ["lx", "ly", "row", "bucket"], "left")
    each = p.groupBy("query_id", "rect_id", "lx", "kx", "ly", "ky").agg(F.median(F.coalesce(F.col("counter"), F.lit(0)) * F.col("sign")).alias("m"))
    sums = each.groupBy("query_id").agg(F.sum("m").alias("e"))
    return boxes.select("query_id").distinct().join(sums, "query_id", "left").select("query_id", F.coalesce("e", F.lit(0.0)).alias("est"))
