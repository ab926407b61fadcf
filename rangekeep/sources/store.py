"""Summaries kept by period in the shared folder, and a data source that reads them with the period pushed down."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, InputPartition

from rangekeep.sources.shared import folder

SCHEMA = "hk string, units bigint, adj_weight double, is_heavy boolean, period int"


def write_store(rows: DataFrame, period: str, meta: dict, path: str | None = None) -> str:
    """Parquet by period under path/data and a row of facts under path/meta; the path is returned."""
    spark = rows.sparkSession
    path = path or f"{folder(spark)}/store-{uuid.uuid4().hex}"
    rows.selectExpr("hk", "units", "adj_weight", "is_heavy", f"cast(`{period}` as int) AS period").write.partitionBy("period").mode("overwrite").parquet(f"{path}/data")
    spark.createDataFrame([(json.dumps(meta),)], "meta string").coalesce(1).write.mode("overwrite").parquet(f"{path}/meta")
    return path


def read_store(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(f"{path}/data")


def read_meta(spark: SparkSession, path: str) -> dict:
    return json.loads(spark.read.parquet(f"{path}/meta").first().meta)


def _open(path: str):
    """(file system, path) of pyarrow for a path or URI that Spark wrote."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)


class _Period(InputPartition):
    def __init__(self, path: str, period: int):
        super().__init__(path)
        self.path, self.period = path, period


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path, self.only = path, None

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("period",):
                self.only = f.value
            else:
                yield f

    def partitions(self):
        from pyarrow import fs

        system, base = _open(f"{self.path}/data")
        found = system.get_file_info(fs.FileSelector(base))
        periods = [(int(x.path.rpartition("period=")[2]), x.path) for x in found if "period=" in x.path]
        kept = [_Period(x, p) for p, x in sorted(periods) if self.only is None or p == self.only]
        return kept or [_Period("", -1)]

    def read(self, part):
        import pyarrow as pa
        import pyarrow.parquet as pq

        if not part.path:
            return
        system, _ = _open(f"{self.path}/data")
        t = pq.read_table(part.path, filesystem=system, partitioning=None)
        t = t.append_column("period", pa.array([part.period] * t.num_rows, pa.int32()))
        yield from t.to_batches()


class SummarySource(DataSource):
    """spark.read.format("rangekeep").option("path", ...) over a store; an equality on period reads that period alone."""

    @classmethod
    def name(cls):
        return "rangekeep"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return _Reader(self.options["path"])


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(SummarySource)
