"""Tables in the folder that driver and executors share."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where nothing is set, a fresh local folder if driver and executors are one process, else an error."""
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="rangekeep-"))
    return sc._jsc.sc().getCheckpointDir().get()


_written: list[tuple[SparkSession, str]] = []


def keep(df: DataFrame) -> DataFrame:
    """Written once and read back: a lost executor or a retried task cannot change what later steps see. Removed when the driver ends."""
    spark = df.sparkSession
    path = f"{folder(spark)}/k-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _written.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


#: Rows and bytes up to which a table is sent to every executor; beyond it the same join shuffles.
BROADCAST_ROWS, BROADCAST_BYTES = 200_000, 64 << 20


def _row_bytes(df: DataFrame) -> Column:
    """About how many bytes a row takes: texts and nested values by their length, all others as two words."""
    out = F.lit(0)
    for field in df.schema:
        kind, c = field.dataType.typeName(), F.col("`" + field.name.replace("`", "``") + "`")
        if kind in ("array", "map", "struct"):
            c, kind = F.to_json(c), "string"
        out = out + (F.coalesce(F.octet_length(c), F.lit(0)) if kind in ("string", "binary") else F.lit(16))
    return out


def small(df: DataFrame, most: int = BROADCAST_ROWS, most_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """df with a broadcast hint if it is measured to hold at most so many rows and bytes; else as it is."""
    size = df.limit(most + 1).select(_row_bytes(df).cast("bigint").alias("b")).agg(F.count("*").alias("n"), F.coalesce(F.sum("b"), F.lit(0)).alias("b")).first()
    return F.broadcast(df) if size.n <= most and size.b <= most_bytes else df


@atexit.register
def _sweep() -> None:
    for spark, path in _written:
        if getattr(spark.sparkContext, "_jsc", None) is not None:
            at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
