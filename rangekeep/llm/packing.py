"""Packing by optimal length buckets.

The lengths of all documents make one histogram; dynamic programming over it picks the bucket boundaries with the
least padding; inside a bucket, every batch holds as many documents as fit the token budget at the bucket's padded length.

Boundaries lie on a grid: exact up to 127, then 64 steps an octave. So the histogram has at most about 64 cells for each
doubling of the longest text, whatever the number of documents; boundaries are optimal on that grid. Documents of one
bucket are in the order of a hash of their id; their ranks come from counts per (bucket, shard) and a window inside
each shard, so no bucket is ever sorted as a whole. A document longer than the budget is a batch of its own.

Null or empty texts have length 0 and lie in the first bucket; repeated rows are packed each; extra columns stay
unless they carry a result's name; an empty table gives an empty result. Fewer distinct lengths than buckets give fewer buckets.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rangekeep.llm._shared import keep, n_words, small

BUCKETS, BUDGET, SHARDS = 12, 32_768, 256


def cell(n: Column) -> Column:
    """Upper end of the grid cell of a length."""
    shift = F.greatest(F.lit(0), F.length(F.bin(F.greatest(n, F.lit(1)) - 1)) - 7).cast("int")
    top = F.call_function("shiftright", F.greatest(n, F.lit(1)) - 1, shift) + 1
    return F.call_function("shiftleft", top, shift)


def boundaries(lengths: list[int], counts: list[int], buckets: int = BUCKETS) -> list[int]:
    """At most `buckets` boundaries among the lengths (rising) with the least padded total."""
    u, c = np.array(lengths, np.float64), np.concatenate([[0], np.cumsum(np.array(counts, np.float64))])
    m = len(u)
    if not m:
        return []
    # cost[i, j]: documents of cells i..j all padded to u[j]
    cost = u[None, :] * (c[1:][None, :] - c[:-1][:, None])
    cost[np.tril_indices(m, -1)] = np.inf
    best, back = cost[0], []
    for _ in range(1, min(buckets, m)):
        whole = np.concatenate([[np.inf], best[:-1]])[:, None] + cost
        back.append(whole.argmin(0))
        best = np.minimum(best, whole[back[-1], np.arange(m)])
        back[-1] = np.where(whole[back[-1], np.arange(m)] <= best, back[-1], 0)
    out, j = [lengths[-1]], m - 1
    for start in reversed(back):
        j = int(start[j]) - 1
        if j < 0:
            break
        out.append(lengths[j])
    return sorted(out)


def pack(docs: DataFrame, text: str = "text", key: str = "doc_id", length: Column | None = None, buckets: int = BUCKETS, budget: int = BUDGET, shards: int = SHARDS) -> DataFrame:
    """docs with n_tokens, bucket (its padded length), batch (number in its bucket) and slot (place in the batch)."""
    made = ("n_tokens", "bucket", "batch", "slot")
    plain = [c for c in docs.columns if c not in made]
    n = (n_words(F.col(text)) if length is None else F.coalesce(length, F.lit(0))).cast("long")
    order = F.xxhash64(F.lit("pack"), F.col(key))
    rows = docs.select(*plain, n.alias("n_tokens"), order.alias("__o")).withColumn("__shard", F.pmod(F.shiftrightunsigned("__o", 20), F.lit(shards)).cast("int"))
    counted = keep(rows.groupBy(cell(F.col("n_tokens")).alias("cell"), F.col("__shard").alias("shard")).count())
    histogram = counted.groupBy("cell").agg(F.sum("count").alias("n")).orderBy("cell").collect()
    edges = boundaries([r.cell for r in histogram], [r.n for r in histogram], buckets)
    edges = edges or [1]

    def of(c: Column) -> Column:
        # no lambda: there, a costly length would be computed anew for every boundary
        out = F.lit(edges[-1]).cast("bigint")
        for e in reversed(edges[:-1]):
            out = F.when(c <= e, F.lit(e).cast("bigint")).otherwise(out)
        return out

    parts = counted.groupBy(of(F.col("cell")).alias("__bucket"), F.col("shard").alias("__at")).agg(F.sum("count").alias("n"))
    before = Window.partitionBy("__bucket").orderBy("__at").rowsBetween(Window.unboundedPreceding, -1)
    starts = parts.select("__bucket", "__at", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("__start"))
    rows = rows.withColumn("bucket", of(F.col("n_tokens"))).join(small(keep(starts)), (F.col("bucket") == F.col("__bucket")) & (F.col("__shard") == F.col("__at")))
    inside = Window.partitionBy("bucket", "__shard").orderBy("__o", key)
    rank = F.col("__start") + F.row_number().over(inside) - 1
    fit = F.greatest(F.lit(1).cast("long"), F.expr(f"{int(budget)} div bucket"))
    rows = rows.withColumn("__rank", rank).withColumn("__fit", fit)
    return rows.select(*plain, "n_tokens", "bucket", F.expr("__rank div __fit").alias("batch"), (F.col("__rank") % F.col("__fit")).cast("int").alias("slot"))


def query(spark, sf_dir: str) -> DataFrame:
    from rangekeep.llm._shared import table

    return pack(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "n_tokens", "bucket", "batch", "slot")
