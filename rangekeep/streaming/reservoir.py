"""Variance-optimal reservoirs of at most s keys: over partitions of a table, and over windows of a stream.

A reservoir takes rows in, and when it holds more than s it samples itself down, each kept row standing for
max(adjusted weight, threshold). Since samples of samples compose, partial reservoirs merge by the same step. A
one-pass sample is blind to structure; none of the range guarantees is claimed here.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangekeep.operators.local import shrink

FAN_IN = 32


#: Rows that a task gathers before it works on them.
AT_ONCE = 65_536
LOW = (1 << 40) - 1


def gathered(batches, rows: int = AT_ONCE):
    """Tables of at least so many rows, but for the last, from record batches."""
    held, n = [], 0
    for b in batches:
        if b.num_rows:
            held.append(b)
            n += b.num_rows
        if n >= rows:
            yield pa.Table.from_batches(held)
            held, n = [], 0
    if held:
        yield pa.Table.from_batches(held)


def _fold(s: int, turn: int):
    """A reservoir over a task's rows; the totals of all rows met (weight in two parts, and number) stay with the first one kept."""

    def run(batches):
        held, adj, now, sums = None, np.zeros(0), turn, [0, 0, 0]
        for t in gathered(batches):
            sums = [x + int(np.asarray(t.column(c)).sum()) for x, c in zip(sums, ("hi", "lo", "met"), strict=True)]
            adj = np.concatenate([adj, np.asarray(t.column("adj_weight"))])
            t = t if held is None else pa.concat_tables([held, t])
            rows, adj = shrink(adj, s, np.asarray(t.column("h")), now)
            held, now = t.take(pa.array(rows)).combine_chunks(), now + 1
        if held is None or not held.num_rows:
            return
        sums = [sums[0] + (sums[1] >> 40), sums[1] & LOW, sums[2]]
        first = np.arange(held.num_rows) == 0
        for c, x in zip(("hi", "lo", "met"), sums, strict=True):
            held = held.set_column(held.schema.get_field_index(c), c, pa.array(np.where(first, x, 0)))
        held = held.set_column(held.schema.get_field_index("adj_weight"), "adj_weight", pa.array(adj))
        yield from held.to_batches()

    return run


def varopt_reservoir(keys: DataFrame, s: int, seed: int = 1, fan_in: int = FAN_IN, columns: tuple[str, ...] = (), totals: bool = False) -> DataFrame:
    """(hk, units, adj_weight, columns...) in one scan: a reservoir for each task, then rounds of merges, each by fan_in fewer tasks.

    A task holds s rows and those that it has just read. With totals, the sums of hi * 2^40 + lo and of met over the
    rows are the weight and the number of all keys.
    """
    extra = [c for c in dict.fromkeys(columns) if c not in ("hk", "units")]
    low = F.col("units").bitwiseAND(F.lit(LOW))
    rows = keys.where("units > 0").select(
        "hk", "units", F.col("units").cast("double").alias("adj_weight"), *extra, F.xxhash64(F.lit(f"reservoir|{seed}"), "hk").alias("h"),
        F.shiftright("units", 40).alias("hi"), low.alias("lo"), F.lit(1).cast("bigint").alias("met"),
    )
    schema, level = rows.schema, 0
    rows = rows.mapInArrow(_fold(s, 0), schema)
    parts = int(keys.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    while parts > 1:
        parts, level = -(-parts // fan_in), level + 1
        # not coalesce, which would hand the scan to as few tasks as the merge
        rows = rows.repartition(parts).mapInArrow(_fold(s, level << 32), schema)
    if level == 0:
        rows = rows.repartition(1).mapInArrow(_fold(s, 1 << 32), schema)
    return rows if totals else rows.drop("h", "hi", "lo", "met")


def event_stream(spark, d: str, files: int = 1):
    """events replayed as a file stream; works for one file and for a folder of files."""
    schema = spark.read.parquet(f"{d}/events.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(f"{d}/event[s].parquet")


def varopt_stream(events: DataFrame, ts: str, key: str, w: str, s: int, window: str = "1 day", late: str = "1 hour", seed: int = 1) -> DataFrame:
    """(start, hk, units, adj_weight) of each window once the watermark has passed it; rows later than that are dropped.

    The state of a window is at most s rows. Each row is a key of its own.
    """
    rows = events.withWatermark(ts, late).where(F.col(w) > 0)
    rows = rows.select(
        F.window(ts, window)["start"].alias("start"), F.window(ts, window)["end"].alias("until"), F.col(key).cast("string").alias("hk"),
        F.floor(F.col(w) * 100 + 0.5).cast("bigint").alias("units"), F.xxhash64(F.lit(f"stream|{seed}"), key).alias("h"), ts,
    )
    out = "start timestamp, hk string, units bigint, adj_weight double"
    state = "hk array<string>, units array<bigint>, adj array<double>, h array<bigint>, turn bigint"

    def step(group, frames, held):
        start, until = group
        if held.hasTimedOut:
            hk, units, adj, _, _ = held.get
            held.remove()
            yield pd.DataFrame({"start": [start] * len(hk), "hk": list(hk), "units": list(units), "adj_weight": list(adj)})
            return
        *lists, turn = held.get if held.exists else ([], [], [], [], 0)
        hk, units, adj, h = (list(x) for x in lists)
        for f in frames:
            hk, units, adj, h = hk + list(f.hk), units + list(f.units), adj + [float(x) for x in f.units], h + list(f.h)
            rows, kept = shrink(np.array(adj), s, np.array(h, np.int64), turn)
            turn += 1
            hk, units, h, adj = [hk[i] for i in rows], [int(units[i]) for i in rows], [int(h[i]) for i in rows], [float(x) for x in kept]
        held.update((hk, units, adj, h, turn))
        edge = int(pd.Timestamp(until).timestamp() * 1000)
        held.setTimeoutTimestamp(max(edge, held.getCurrentWatermarkMs() + 1))
        return
        yield

    return rows.groupBy("start", "until").applyInPandasWithState(step, out, state, "append", "EventTimeTimeout")


def run_to_table(stream: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there and returns what it wrote under path."""
    spark = stream.sparkSession
    kept = stream.writeStream.format("parquet").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/log").outputMode(mode).trigger(availableNow=True).start()
    kept.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def fold_batches(stream: DataFrame, path: str, fold) -> None:
    """Runs a stream; fold(rows of a batch, folder, number) keeps what it likes. A repeated batch overwrites its own folder."""

    def each(rows: DataFrame, number: int) -> None:
        fold(rows, f"{path}/batch={number}", number)

    q = stream.writeStream.foreachBatch(each).option("checkpointLocation", f"{path}-log").trigger(availableNow=True).start()
    q.awaitTermination()
