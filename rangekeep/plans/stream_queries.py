"""Streams over the replayed events, next to what a batch says."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from rangekeep.operators.ipps import threshold
from rangekeep.operators.keys import keyed, keyed_sql
from rangekeep.plans.sampling_queries import key_set, key_set_sql
from rangekeep.sources.shared import folder
from rangekeep.streaming import reservoir as R

QUERIES, SQL = {}, {}


def query(name, sql=None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def fresh(spark, kind):
    return f"{folder(spark)}/{kind}-{uuid.uuid4().hex}"


@query("varopt_reservoir_docs", f"WITH {key_set_sql('docs')} SELECT least(300, count(*))::BIGINT AS n, least(300, count(*))::BIGINT AS distinct_keys, sum(units)::BIGINT AS total FROM k WHERE units > 0")
def _(spark, d):
    r = R.varopt_reservoir(key_set(spark, d, "docs"), 300)
    return r.agg(F.count("*").alias("n"), F.countDistinct("hk").alias("distinct_keys"), F.round(F.sum("adj_weight"), 0).cast("bigint").alias("total"))


@query("stream_window_counts", "WITH w AS (SELECT date_trunc('day', ts) AS day, count(*) AS n FROM events GROUP BY 1) SELECT strftime(day, '%Y-%m-%d') AS day, n FROM w WHERE day + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)")
def _(spark, d):
    """Tumbling days of the stream, out as the watermark passes them; the batch twin counts the days that ended by then."""
    e = R.event_stream(spark, d).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")
    s = e.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return R.run_to_table(s.select("w", "n"), fresh(spark, "stream")).select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n")


@query("stream_reservoir", "WITH w AS (SELECT date_trunc('day', ts) AS day, count(*) FILTER (value > 0) AS n, sum(floor(value * 100 + 0.5::DOUBLE)::BIGINT)::BIGINT AS total FROM events GROUP BY 1) SELECT strftime(day, '%Y-%m-%d') AS day, least(50, n)::BIGINT AS n, true AS close FROM w WHERE day + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)")
def _(spark, d):
    """A reservoir of 50 events a day over the stream; its adjusted weights add up to the day's total."""
    e = R.event_stream(spark, d).withColumn("ts", F.col("ts").cast("timestamp"))
    rows = R.run_to_table(R.varopt_stream(e, "ts", "event_id", "value", 50), fresh(spark, "stream"))
    got = rows.groupBy(F.date_format("start", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("n"), F.sum("adj_weight").alias("e"))
    b = spark.read.parquet(f"{d}/events.parquet").where("value > 0").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.sum(F.floor(F.col("value") * 100 + 0.5)).alias("t"))
    return got.join(b, "day").select("day", "n", (F.abs(F.col("e") / F.col("t") - 1) < 1e-9).alias("close"))


@query("stream_batch_summaries", f"WITH k AS ({keyed_sql('(SELECT event_id, value FROM events WHERE value > 0) x', ['event_id'], 'value', 100)}) SELECT 100::BIGINT AS n, sum(units)::BIGINT AS total, true AS close FROM k")
def _(spark, d):
    """Each micro-batch leaves a summary; they are sampled again to one of 100 keys, with the whole total."""
    from rangekeep.operators import structures as S
    from rangekeep.operators.estimate import merge

    path = fresh(spark, "batches")

    def fold(rows, to, number):
        k = keyed(rows.where("value > 0"), ["event_id"], "value", 100)
        S.varopt(k, 200, seed=number + 1).rows.select("event_id", "hk", "adj_weight").write.mode("overwrite").parquet(to)

    R.fold_batches(R.event_stream(spark, d), path, fold)
    rows = spark.read.parquet(path).drop("batch")
    th = threshold(rows.select(F.floor(F.col("adj_weight") + 0.5).cast("bigint").alias("units")), 100)
    out = merge([S.Summary(rows, th, 1, "varopt")], 100).rows
    truth = spark.read.parquet(f"{d}/events.parquet").where("value > 0").agg(F.sum(F.floor(F.col("value") * 100 + 0.5)).alias("total"))
    # merged weights are whole units, so each merge rounds every key's by half a unit at most
    got = out.agg(F.count("*").alias("n"), F.sum("adj_weight").alias("e")).join(truth, F.lit(True))
    return got.select("n", "total", (F.abs(F.col("e") / F.col("total") - 1) < 1e-4).alias("close"))


@query("stream_dedup", "SELECT count(*) AS n, count(DISTINCT event_id) AS ids, min(event_id) AS least, max(event_id) AS most FROM events")
def _(spark, d):
    """Every event twice on the stream, once within the watermark; then, as the stream goes on from its checkpoint, rows
    under new ids that lie behind the watermark, which are too late and left out."""
    at = fresh(spark, "dedup")
    rows = spark.read.parquet(f"{d}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    late = rows.select((-1 - F.col("event_id")).alias("event_id"), (F.col("ts") - F.expr("INTERVAL 4000 DAYS")).alias("ts"))
    for part in (rows.unionByName(rows), late):
        part.write.mode("append").parquet(f"{at}/in")
        sent = spark.readStream.schema(rows.schema).parquet(f"{at}/in").withWatermark("ts", "1 hour")
        out = R.run_to_table(sent.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), at)
    return out.agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("ids"), F.min("event_id").alias("least"), F.max("event_id").alias("most"))


@query("stream_static_join", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def _(spark, d):
    """Stream rows meet a table that stays as it is."""
    e = R.event_stream(spark, d).select("event_id", "user_id")
    c = spark.read.parquet(f"{d}/customer.parquet").select("c_custkey", "c_mktsegment")
    rows = R.run_to_table(e.join(c, e.user_id == c.c_custkey).select("event_id", "c_mktsegment"), fresh(spark, "static"))
    return rows.groupBy("c_mktsegment").agg(F.count("*").alias("n"))


def queries():
    return dict(QUERIES)


def oracle_sql():
    return dict(SQL)
