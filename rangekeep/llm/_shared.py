"""Small pieces the text-corpus operators share: words, tables in the shared folder, Arrow chunks."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Iterable, Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Size up to which a table is broadcast; beyond it the same join shuffles.
BROADCAST_ROWS, BROADCAST_BYTES = 200_000, 64 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def lower_az(c: Column) -> Column:
    return F.translate(c, UPPER, LOWER)


def n_words(c: Column) -> Column:
    """Number of maximal runs of characters other than ASCII blanks; 0 for null."""
    return F.regexp_count(F.coalesce(c, F.lit("")), F.lit("[^\\x20\\x09-\\x0D]+")).cast("long")


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; a fresh one where that is unset and they are one process."""
    sc = spark.sparkContext
    held = sc._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return held.get()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not sc.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="rangekeep-"))
    return sc._jsc.sc().getCheckpointDir().get()


_written: list[tuple[SparkSession, str]] = []


def keep(df: DataFrame, spark: SparkSession | None = None) -> DataFrame:
    """Write df to the shared folder as Parquet and read it back: cuts lineage and survives lost executors."""
    return keep_parts([df], spark)


def keep_parts(parts: Iterable[DataFrame], spark: SparkSession | None = None) -> DataFrame:
    """The rows of all parts as one kept table. They are written one after the other, so that the disk holds one part's shuffles at a time."""
    path = schema = None
    for df in parts:
        spark = spark or df.sparkSession
        if path is None:
            path, schema = f"{shared_folder(spark)}/t-{uuid.uuid4().hex}", df.schema
            _written.append((spark, path))
        df.write.mode("append").parquet(path)
        free_shuffles(spark)
    out = spark.read.schema(schema).parquet(path)
    out._kept_at = path
    return out


def free_shuffles(spark: SparkSession) -> None:
    """Shuffle files go when the driver's JVM finds that no plan holds them, which on a quiet driver may be after the last job:
    a chain of jobs would fill the disk with the sum of its shuffles instead of the largest."""
    spark.sparkContext._jvm.System.gc()


def written() -> int:
    """How many tables keep() has written so far, for forget_since()."""
    return len(_written)


def forget_since(mark: int, *but: DataFrame) -> None:
    """Delete the tables that keep() wrote after the mark, but for these."""
    stay = {getattr(df, "_kept_at", None) for df in but}
    for spark, path in _written[mark:]:
        if path not in stay:
            _delete(spark, path)
    _written[mark:] = [x for x in _written[mark:] if x[1] in stay]


def forget(*frames: DataFrame) -> None:
    """Delete tables that keep() wrote and nothing reads any more."""
    for df in frames:
        path = getattr(df, "_kept_at", None)
        if path:
            _delete(df.sparkSession, path)


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


@atexit.register
def _sweep() -> None:
    for spark, path in _written:
        if getattr(spark.sparkContext, "_jsc", None) is not None:
            _delete(spark, path)


#: Rows of an Arrow batch for whole texts, so that a worker's memory follows a few texts and not ten thousand.
ARROW_ROWS = 500


def short_batches(spark: SparkSession) -> None:
    """Arrow batches of at most ARROW_ROWS rows from here on; a session's own smaller setting stays."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(name))
    if now <= 0 or now > ARROW_ROWS:
        spark.conf.set(name, str(ARROW_ROWS))


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


def pieces(texts, most_bytes: int = 4_000_000) -> Iterator[tuple[int, int]]:
    """Index ranges of a sequence of byte strings (or None) holding about most_bytes each; a longer text is alone."""
    return spans([len(t) if t else 0 for t in texts], most_bytes)


def spans(lengths, most_bytes: int) -> Iterator[tuple[int, int]]:
    start = held = 0
    for i, n in enumerate(lengths):
        if held and held + n > most_bytes:
            yield start, i
            start, held = i, 0
        held += n
    if start < len(lengths):
        yield start, len(lengths)


def chunks(column, most_bytes: int = 2_000_000) -> Iterator[tuple[int, int, list]]:
    """(from, to, values) of an Arrow column of byte strings, about most_bytes of them as Python values at a time."""
    import pyarrow.compute as pc

    for lo, hi in spans(pc.fill_null(pc.binary_length(column), 0).to_pylist(), most_bytes):
        yield lo, hi, column.slice(lo, hi - lo).to_pylist()


def trim() -> None:
    """Give memory that is free back to the machine: a Python worker waits for its next task beside its executor."""
    import ctypes
    import gc

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    if hasattr(libc := ctypes.CDLL(None), "malloc_trim"):
        libc.malloc_trim(0)
