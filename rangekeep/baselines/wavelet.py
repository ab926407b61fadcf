"""Two-dimensional standard Haar transform of a weighted key set, cut to its largest coefficients.

A basis function of an axis of 2^b values has number 0 (constant) or 2^l + k (level l, block k of 2^(b-l) values:
plus on its left half, minus on the right). A coefficient is a signed sum of weights times a power of two's root, so
the signed sums stay whole numbers and any order of summing gives the same. One axis is folded before the other, which
turns the (bx+1)(by+1) contributions of a point into (bx+1) of each point and (by+1) of each partial sum.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Log2 of the values in a block of the longer axis, whose own functions one task makes in memory.
BLOCK = 9
#: Points of a task's share of the digits in build(), up to about twice as many; a point makes (bits_x + 1)(bits_y + 1) contributions.
BLOCK_POINTS = 1 << 15


def _functions(v: Column, bits: int) -> Column:
    """Array of structs (i, sign) of the basis functions that a value meets."""

    def one(level: Column) -> Column:
        block = F.call_function("shiftright", v, bits - level)
        half = F.call_function("shiftright", v, bits - 1 - level) % 2
        return F.struct((F.call_function("shiftleft", F.lit(1).cast("bigint"), level) + block).alias("i"), (1 - 2 * half).cast("bigint").alias("sign"))

    rest = F.transform(F.sequence(F.lit(0), F.lit(bits - 1)), one) if bits else F.array().cast("array<struct<i:bigint,sign:bigint>>")
    return F.concat(F.array(F.struct(F.lit(0).cast("bigint").alias("i"), F.lit(1).cast("bigint").alias("sign"))), rest)


def size_log(i: Column, bits: int) -> Column:
    """Log2 of the support of basis function i."""
    return F.when(i == 0, bits).otherwise(bits - (F.length(F.bin(i)) - 1)).cast("int")


def _exploded(points: DataFrame, x: str, y: str, w: str, bits_x: int, bits_y: int, only: DataFrame | None = None, on_x: Column | None = None) -> DataFrame:
    """build() for few points or few coefficients: a row for each function of x that a point meets, or that on_x lists."""
    a = points.select(F.explode(_functions(F.col(x), bits_x) if on_x is None else on_x).alias("f"), F.col(y).alias("y"), F.col(w).alias("w"))
    if only is not None:
        a = a.join(F.broadcast(only.select(F.col("ix").alias("__i")).distinct()), F.col("f.i") == F.col("__i"), "left_semi")
    a = a.groupBy(F.col("f.i").alias("ix"), "y").agg(F.sum(F.col("w") * F.col("f.sign")).alias("w"))
    b = a.select("ix", F.explode(_functions(F.col("y"), bits_y)).alias("f"), "w")
    if only is not None:
        pairs = only.select(F.col("ix").alias("__x"), F.col("iy").alias("__y")).distinct()
        b = b.join(F.broadcast(pairs), (F.col("ix") == F.col("__x")) & (F.col("f.i") == F.col("__y")), "left_semi")
    b = b.groupBy("ix", F.col("f.i").alias("iy")).agg(F.sum(F.col("w") * F.col("f.sign")).alias("signed")).where("signed <> 0")
    return _normalised(b, bits_x, bits_y)


def _normalised(sums: DataFrame, bits_x: int, bits_y: int) -> DataFrame:
    e = size_log(F.col("ix"), bits_x) + size_log(F.col("iy"), bits_y)
    return sums.withColumn("c", F.col("signed") / F.sqrt(F.pow(F.lit(2.0), e)))


def build(points: DataFrame, x: str, y: str, w: str, bits_x: int, bits_y: int, only: DataFrame | None = None) -> DataFrame:
    """All non-zero coefficients: ix, iy, signed (the signed sum), c (normalised). With only (ix, iy; a workload's few
    thousand rows) those that it names, and contributions to others are dropped before anything is shuffled.

    Function 2^l + k of value v is v + 2^bits without its last bits - l binary digits, so that functions are the
    beginnings of their values' digits, also where values pass their bits and levels share numbers. Values with the same
    first digits go to one task, which makes all functions with these digits in memory; points are shuffled once. The
    shorter functions see the values of a task as one for each length.
    """
    if only is not None:
        return _exploded(points, x, y, w, bits_x, bits_y, only)
    if bits_y > bits_x:
        made = build(points, y, x, w, bits_y, bits_x)
        return made.select(F.col("iy").alias("ix"), F.col("ix").alias("iy"), "signed", "c")
    spark = points.sparkSession
    digits = min(bits_x + 1, max(1, (points.count() // BLOCK_POINTS).bit_length()))
    a = points.select((F.col(x).cast("bigint") + (1 << bits_x)).alias("a"), F.col(y).cast("bigint").alias("b"), F.col(w).cast("bigint").alias("w"))
    length = F.length(F.bin("a"))
    a = a.select("*", length.alias("n"), F.call_function("shiftright", F.col("a"), length - digits).alias("first"))
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    # a number of its own: few bytes make many coefficients, so these partitions are not to be merged
    own = a.select("a", "b", "w", "first").repartition(tasks, "first").groupBy("first").applyInArrow(_of_digits(digits, bits_x, bits_y), "ix long, iy long, signed long")
    # beginnings shorter than the task's digits, as far as a value of that length has them
    folded = a.groupBy("n", "first", "b").agg(F.sum("w").alias("w"))
    fewer = F.filter(F.sequence(F.lit(0), F.lit(digits - 1)), lambda k: (k > 0) & (k <= F.lit(bits_x + digits) - F.col("n")))
    at = lambda k: F.call_function("shiftright", F.col("first"), k)
    short = F.transform(fewer, lambda k: F.struct(at(k).alias("i"), (1 - 2 * (at(k - 1) % 2)).cast("bigint").alias("sign")))
    constant = F.array(F.struct(F.lit(0).cast("bigint").alias("i"), F.lit(1).cast("bigint").alias("sign")))
    over = _exploded(folded, "first", "b", "w", bits_x, bits_y, on_x=F.concat(constant, short))
    return _normalised(own, bits_x, bits_y).unionByName(over)


def _sorted(a: np.ndarray, b: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows (a, b, w) in order, those with the same (a, b) summed."""
    order = np.lexsort((b, a))
    a, b, w = a[order], b[order], w[order]
    starts = _starts(a, b)
    return a[starts], b[starts], np.add.reduceat(w, starts)


def _starts(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])]))


def _of_digits(digits: int, bits_a: int, bits_b: int):
    """Points (a with 2^bits_a added, b, w) that share their first digits -> all coefficients whose function on a has these."""

    def on_b(i: np.ndarray, b: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Sums w of values b under functions i, in order -> coefficients."""
        starts = np.flatnonzero(np.concatenate([[True], i[1:] != i[:-1]]))
        parts = [(i[starts], np.zeros(len(starts), np.int64), np.add.reduceat(w, starts))]
        longer = bool(b.max() >> (bits_b + 1))
        for _ in range(bits_b):
            up, sign = b >> 1, 1 - 2 * (b & 1)
            starts = _starts(i, up)
            parts.append((i[starts], up[starts], np.add.reduceat(w * sign, starts)))
            i, b, w = i[starts], up[starts], np.add.reduceat(w, starts)
        ix, iy, signed = (np.concatenate(p) for p in zip(*parts, strict=True))
        if longer:  # levels share numbers
            ix, iy, signed = _sorted(ix, iy, signed)
        left = signed != 0
        return ix[left], iy[left], signed[left]

    def run(t: pa.Table) -> pa.Table:
        a, b, w = (t.column(n).to_numpy().astype(np.int64) for n in ("a", "b", "w"))
        if np.abs(w.astype(np.float64)).sum() >= 2.0**62:
            raise OverflowError("the weight of a block passes 62 bits")
        a, b, w = _sorted(a, b + (1 << bits_b), w)
        lengths, sums = np.array([v.bit_length() for v in a.tolist()]), {}
        for n in np.unique(lengths).tolist():
            i, at, v = (c[lengths == n] for c in (a, b, w))
            for now in range(n - 1, max(digits, n - bits_a) - 1, -1):
                order = np.lexsort((at, i >> 1))
                up, at, sign, v = (i >> 1)[order], at[order], (1 - 2 * (i & 1))[order], v[order]
                starts = _starts(up, at)
                sums.setdefault(now, []).append((up[starts], at[starts], np.add.reduceat(v * sign, starts)))
                i, at, v = up[starts], at[starts], np.add.reduceat(v, starts)
        out = [(np.zeros(0, np.int64),) * 3]
        for parts in sums.values():
            out.append(on_b(*(parts[0] if len(parts) == 1 else _sorted(*(np.concatenate(p) for p in zip(*parts, strict=True))))))
        return pa.table({n: np.concatenate(c) for n, c in zip(("ix", "iy", "signed"), zip(*out, strict=True), strict=True)})

    return run


def largest(coefficients: DataFrame, s: int) -> DataFrame:
    return coefficients.orderBy(F.desc(F.abs("c")), "ix", "iy").limit(s)


def _first(ix: np.ndarray, iy: np.ndarray, signed: np.ndarray, c: np.ndarray, s: int) -> np.ndarray:
    """Rows of the s largest, in the order of largest()."""
    size, at = np.abs(c), np.arange(len(c))
    if len(c) > s:
        at = np.flatnonzero(size >= np.partition(size, len(c) - s)[len(c) - s])
    return at[np.lexsort((iy[at], ix[at], -size[at]))[:s]]


def _own(low: int, bits_a: int, bits_b: int, s: int, swapped: bool):
    """Points (a, b, w) of one block of 2^low values of a -> its s largest coefficients whose support on a lies in the block,
    and a row (-1, -1) with the number of all of them that aren't zero."""

    def run(t: pa.Table) -> pa.Table:
        a, b, w = (t.column(n).to_numpy().astype(np.int64) for n in ("a", "b", "w"))
        on_b = [(np.zeros(len(b), np.int64), np.ones(len(b), np.int64))]
        on_b += [((1 << m) + (b >> (bits_b - m)), 1 - 2 * ((b >> (bits_b - 1 - m)) & 1)) for m in range(bits_b)]
        held, made = [np.zeros(0, np.int64)] * 3 + [np.zeros(0)], 0
        for level in range(bits_a - low, bits_a):
            ia, wa = (1 << level) + (a >> (bits_a - level)), w * (1 - 2 * ((a >> (bits_a - 1 - level)) & 1))
            for m, (ib, sb) in enumerate(on_b):
                key = (ia << (bits_b + 1)) | ib
                order = np.argsort(key, kind="stable")
                key = key[order]
                starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
                signed, key = np.add.reduceat((wa * sb)[order], starts), key[starts]
                key, signed = key[signed != 0], signed[signed != 0]
                made += len(key)
                c = signed / np.sqrt(2.0 ** (bits_a - level + (bits_b if m == 0 else bits_b - m + 1)))
                ka, kb = key >> (bits_b + 1), key & ((1 << (bits_b + 1)) - 1)
                held = [np.concatenate(p) for p in zip(held, (kb, ka, signed, c) if swapped else (ka, kb, signed, c), strict=True)]
            at = _first(*held, s)
            held = [x[at] for x in held]
        ix, iy, signed, c = (np.append(x, v) for x, v in zip(held, (-1, -1, made, 0.0), strict=True))
        return pa.table({"ix": ix, "iy": iy, "signed": signed, "c": c})

    return run


def top(points: DataFrame, x: str, y: str, w: str, bits_x: int, bits_y: int, s: int) -> DataFrame:
    """The s largest of build()'s coefficients without writing or shuffling all of them, and a row (-1, -1) whose signed is
    the number of all. Values lie within their bits.

    The longer axis is cut into blocks. Functions within a block rest on its points alone, so that one task makes them
    and keeps its s largest; the wider ones see a block as one value, and there are few of them.
    """
    swapped = bits_y > bits_x
    (a, bits_a), (b, bits_b) = ((y, bits_y), (x, bits_x)) if swapped else ((x, bits_x), (y, bits_y))
    low = min(bits_a, BLOCK)
    rows = points.select(F.col(a).cast("bigint").alias("a"), F.col(b).cast("bigint").alias("b"), F.col(w).cast("bigint").alias("w"))
    own = rows.groupBy(F.shiftright("a", low)).applyInArrow(_own(low, bits_a, bits_b, s, swapped), "ix long, iy long, signed long, c double")
    folded = rows.groupBy(F.shiftright("a", low).alias("a"), "b").agg(F.sum("w").alias("w"))
    over = _exploded(folded, "a", "b", "w", bits_a - low, bits_b)
    e = size_log(F.col("ix"), bits_a - low) + size_log(F.col("iy"), bits_b) + low
    over = over.withColumn("c", F.col("signed") / F.sqrt(F.pow(F.lit(2.0), e)))
    if swapped:
        over = over.select(F.col("iy").alias("ix"), F.col("ix").alias("iy"), "signed", "c")
    made = over.agg(F.count("*").alias("signed")).select(F.lit(-1).cast("bigint").alias("ix"), F.lit(-1).cast("bigint").alias("iy"), "signed", F.lit(0.0).alias("c"))
    every = own.unionByName(largest(over, s)).unionByName(made)
    counts = every.where("ix < 0").groupBy("ix", "iy").agg(F.sum("signed").alias("signed"), F.max("c").alias("c"))
    return largest(every.where("ix >= 0"), s).unionByName(counts)


def contributions(n: int, bits_x: int, bits_y: int) -> int:
    """Coefficients touched by n points one by one."""
    return n * (bits_x + 1) * (bits_y + 1)


def _overlap(i: Column, lo: Column, hi: Column, bits: int) -> Column:
    """Values of [lo, hi) under the plus half of function i less those under its minus half; for 0 all values."""
    e = size_log(i, bits)
    size = F.call_function("shiftleft", F.lit(1).cast("bigint"), e)
    start = F.when(i == 0, F.lit(0).cast("bigint")).otherwise((i % F.call_function("shiftleft", F.lit(1).cast("bigint"), bits - e)) * size)
    mid, end = start + F.floor(size / 2).cast("bigint"), start + size
    part = lambda a, b: F.greatest(F.lit(0).cast("bigint"), F.least(hi, b) - F.greatest(lo, a))
    return F.when(i == 0, part(start, end)).otherwise(part(start, mid) - part(mid, end))


def _felt(boxes: DataFrame, bits_x: int, bits_y: int) -> DataFrame:
    """Boxes with the numbers ix, iy of the functions that their ends meet, two a level at most, and of the constants."""

    def felt(lo: str, hi: str, bits: int, as_: str):
        def level(n: Column) -> Column:
            first = F.call_function("shiftright", F.col(lo), bits - n)
            last = F.call_function("shiftright", F.col(hi) - 1, bits - n)
            one = F.call_function("shiftleft", F.lit(1).cast("bigint"), n)
            return F.array_distinct(F.array(one + first, one + last))

        rest = F.flatten(F.transform(F.sequence(F.lit(0), F.lit(bits - 1)), level)) if bits else F.array().cast("array<bigint>")
        return F.explode(F.concat(F.array(F.lit(0).cast("bigint")), rest)).alias(as_)

    return boxes.where("x_lo < x_hi AND y_lo < y_hi").select("*", felt("x_lo", "x_hi", bits_x, "ix")).select("*", felt("y_lo", "y_hi", bits_y, "iy"))


def felt(boxes: DataFrame, bits_x: int, bits_y: int) -> DataFrame:
    """(ix, iy) of all coefficients that a box may feel."""
    return _felt(boxes, bits_x, bits_y).select("ix", "iy").distinct()


def query_all(coefficients: DataFrame, boxes: DataFrame, bits_x: int, bits_y: int) -> DataFrame:
    """(query_id, est) from any number of coefficients: each axis's functions that a box feels are listed from the box, at most
    two a level (at its ends) and those that cover it, and met by equality."""
    rows = _felt(boxes, bits_x, bits_y)
    ov_x, ov_y = _overlap(F.col("ix"), F.col("x_lo"), F.col("x_hi"), bits_x), _overlap(F.col("iy"), F.col("y_lo"), F.col("y_hi"), bits_y)
    rows = rows.withColumn("by", ov_x * ov_y / F.pow(F.lit(2.0), size_log(F.col("ix"), bits_x) + size_log(F.col("iy"), bits_y))).where("by <> 0")
    sums = rows.join(coefficients.select("ix", "iy", "signed"), ["ix", "iy"]).groupBy("query_id").agg(F.sum(F.col("signed") * F.col("by")).alias("e"))
    return boxes.select("query_id").distinct().join(sums, "query_id", "left").select("query_id", F.coalesce("e", F.lit(0.0)).alias("est"))


def query(coefficients: DataFrame, boxes: DataFrame, bits_x: int, bits_y: int, method: str = "overlap") -> DataFrame:
    """(query_id, est): sums of boxes from the kept coefficients, each box at once or by its dyadic pieces."""
    from rangekeep.baselines.dyadic import pieces

    if method == "dyadic":
        p = pieces(boxes, bits_x, bits_y)
        left = lambda k, l: F.call_function("shiftleft", F.col(k), F.col(l).cast("int"))  # noqa: E731, E741
        boxes = p.select("query_id", "rect_id", left("kx", "lx").alias("x_lo"), (left("kx", "lx") + F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("lx").cast("int"))).alias("x_hi"),
                         left("ky", "ly").alias("y_lo"), (left("ky", "ly") + F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("ly").cast("int"))).alias("y_hi"))
    ov_x = _overlap(F.col("ix"), F.col("x_lo"), F.col("x_hi"), bits_x)
    ov_y = _overlap(F.col("iy"), F.col("y_lo"), F.col("y_hi"), bits_y)
    e = size_log(F.col("ix"), bits_x) + size_log(F.col("iy"), bits_y)
    # coefficients are at most s rows, boxes a workload's few thousand
    rows = boxes.join(F.broadcast(coefficients.select("ix", "iy", "signed")), (ov_x != 0) & (ov_y != 0))
    # the shares first: a sum times an area passes 63 bits on large tables
    sums = rows.groupBy("query_id").agg(F.sum(F.col("signed") * (ov_x * ov_y / F.pow(F.lit(2.0), e))).alias("e"))
    return boxes.select("query_id").distinct().join(sums, "query_id", "left").select("query_id", F.coalesce("e", F.lit(0.0)).alias("est"))
