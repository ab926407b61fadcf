"""Operators around the samplers: sources, sinks, joins, aggregates, windows, sets, functions, SQL, UDFs; each with its DuckDB twin."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from rangekeep.operators import structures as S
from rangekeep.plans.sampling_queries import DOCS, bounds_sql, docs_summary
from rangekeep.sources import table, views
from rangekeep.sources.shared import folder, keep

QUERIES, SQL = {}, {}


def query(name, sql=None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def cents(c):
    return F.floor(F.col(c) * 100 + 0.5).cast("bigint")


CENTS = "floor({} * 100 + 0.5::DOUBLE)::BIGINT"
PRICE = CENTS.format("l_extendedprice")


# sources and sinks
@query("scan_prune", f"SELECT l_linestatus, count(*) AS n, sum({PRICE})::BIGINT AS units FROM lineitem WHERE l_returnflag = 'R' AND l_suppkey < 50 GROUP BY 1")
def _(spark, d):
    return table(spark, d, "lineitem").where("l_returnflag = 'R' AND l_suppkey < 50").groupBy("l_linestatus").agg(F.count("*").alias("n"), F.sum(cents("l_extendedprice")).alias("units"))


ROUND_TRIP = f"{DOCS} SELECT f.format, count(*) AS n, sum(units)::BIGINT AS units FROM smp, (SELECT unnest(['csv', 'json', 'orc', 'parquet']) AS format) f GROUP BY 1"


@query("sink_roundtrip", ROUND_TRIP)
def _(spark, d):
    """A summary through four formats and back."""
    import uuid

    rows, out = keep(docs_summary(spark, d).rows.select("doc_id", "hk", "units", "adj_weight")), None
    for f in ("csv", "json", "orc", "parquet"):
        path = f"{folder(spark)}/{f}-{uuid.uuid4().hex}"
        rows.write.format(f).save(path)
        part = spark.read.schema(rows.schema).format(f).load(path).agg(F.lit(f).alias("format"), F.count("*").alias("n"), F.sum("units").alias("units"))
        out = part if out is None else out.unionByName(part)
    return out.select("format", "n", "units")


STORE = f"""WITH y AS (SELECT year(l_shipdate)::INT AS period, l_shipdate, sum({PRICE})::BIGINT AS units FROM lineitem GROUP BY 1, 2), t AS (SELECT period, count(*) AS n, sum(units)::BIGINT AS total FROM y GROUP BY 1)"""


def _stored(spark, d):
    from rangekeep.operators.periods import summarize_by
    from rangekeep.plans.sampling_queries import key_set
    from rangekeep.sources.store import write_store

    k = key_set(spark, d, "shipday").withColumn("period", F.year("l_shipdate")).withColumn("l_shipdate", F.date_format("l_shipdate", "yyyy-MM-dd"))
    rows = summarize_by(k, "period", 20, ["l_shipdate"])
    return write_store(rows, "period", {"s": 20, "seed": 1, "structure": "order"})


@query("summary_store", STORE + " SELECT period, least(20, n)::BIGINT AS n, total, true AS close FROM t WHERE period >= 1999")
def _(spark, d):
    """Summaries kept by period; only the asked periods are read."""
    from rangekeep.sources.store import read_store

    path = _stored(spark, d)
    got = read_store(spark, path).where("period >= 1999").groupBy("period").agg(F.count("*").alias("n"), F.sum("adj_weight").alias("e"))
    truth = table(spark, d, "lineitem").groupBy(F.year("l_shipdate").alias("period")).agg(F.sum(cents("l_extendedprice")).alias("total"))
    return got.join(truth, "period").select("period", "n", "total", (F.abs(F.col("e") / F.col("total") - 1) < 1e-9).alias("close"))


@query("ds_summary", STORE + " SELECT period, least(20, n)::BIGINT AS n FROM t WHERE period = 2000")
def _(spark, d):
    """The same store through the package's own data source, with the period pushed down."""
    from rangekeep.sources.store import register

    path = _stored(spark, d)
    register(spark)
    got = spark.read.format("rangekeep").option("path", path).load().where("period = 2000")
    return got.groupBy("period").agg(F.count("*").alias("n"))


# joins
BOXES = "(VALUES (0, 0, 100, 0, 50), (1, 50, 200, 20, 80), (2, 500, 600, 0, 100)) AS b(q, x0, x1, y0, y1)"


@query("join_boxes", f"SELECT q::INT AS q, count(*) AS n FROM lineitem JOIN {BOXES} ON l_partkey >= x0 AND l_partkey < x1 AND l_suppkey >= y0 AND l_suppkey < y1 GROUP BY 1")
def _(spark, d):
    b = spark.createDataFrame([(0, 0, 100, 0, 50), (1, 50, 200, 20, 80), (2, 500, 600, 0, 100)], "q int, x0 int, x1 int, y0 int, y1 int")
    on = (F.col("l_partkey") >= F.col("x0")) & (F.col("l_partkey") < F.col("x1")) & (F.col("l_suppkey") >= F.col("y0")) & (F.col("l_suppkey") < F.col("y1"))
    return table(spark, d, "lineitem").join(F.broadcast(b), on).groupBy("q").agg(F.count("*").alias("n"))


@query("join_hierarchy", "SELECT r_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def _(spark, d):
    c, n, r = (table(spark, d, t) for t in ("customer", "nation", "region"))
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("customers"))


_JOIN = f"SELECT o_orderpriority, sum({PRICE})::BIGINT AS units FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _hinted(hint):
    def run(spark, d):
        li, o = table(spark, d, "lineitem"), table(spark, d, "orders")
        return li.join(o.hint(hint), li.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.sum(cents("l_extendedprice")).alias("units"))

    return run


query("join_smj", _JOIN)(_hinted("merge"))
query("join_shj", _JOIN)(_hinted("shuffle_hash"))


@query("join_outer_truth", DOCS + ", e AS (SELECT source, sum(adj_weight) AS e FROM smp WHERE lang = 'fr' GROUP BY 1), t AS (SELECT source, sum(n_chars)::BIGINT AS truth FROM documents GROUP BY 1) SELECT t.source, truth, round(coalesce(e, 0), 2) AS est FROM t FULL JOIN e ON t.source = e.source")
def _(spark, d):
    e = docs_summary(spark, d).rows.where("lang = 'fr'").groupBy("source").agg(F.sum("adj_weight").alias("e"))
    t = table(spark, d, "documents").groupBy("source").agg(F.sum("n_chars").alias("truth"))
    return t.join(e, "source", "full").select("source", "truth", F.round(F.coalesce("e", F.lit(0.0)), 2).alias("est"))


@query("join_semi", "SELECT source, count(*) AS n FROM documents WHERE doc_id IN (SELECT doc_id FROM labels) GROUP BY 1")
def _(spark, d):
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left_semi").groupBy("source").agg(F.count("*").alias("n"))


@query("join_anti", "SELECT source, count(*) AS n FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels) GROUP BY 1")
def _(spark, d):
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left_anti").groupBy("source").agg(F.count("*").alias("n"))


@query("join_asof", """WITH e AS (SELECT event_id, user_id, ts, event_type FROM events), v AS (SELECT user_id, ts, max(event_id) AS event_id FROM e WHERE event_type = (SELECT min(event_type) FROM events) GROUP BY 1, 2)
SELECT e.event_id, v.event_id AS last_first_kind FROM e ASOF LEFT JOIN v ON e.user_id = v.user_id AND e.ts >= v.ts""")
def _(spark, d):
    """Each event with the user's last event of the first kind at or before it, by a union and a window."""
    e = table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    first = e.agg(F.min("event_type").alias("k"))
    left = e.select("event_id", "user_id", "ts", F.lit(None).cast("bigint").alias("mark"), F.lit(1).alias("side"))
    right = e.join(F.broadcast(first), F.col("event_type") == F.col("k")).groupBy("user_id", "ts").agg(F.max("event_id").alias("mark"))
    right = right.select(F.lit(None).cast("bigint").alias("event_id"), "user_id", "ts", "mark", F.lit(0).alias("side"))
    run = Window.partitionBy("user_id").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    return left.unionByName(right).withColumn("last_first_kind", F.last("mark", ignorenulls=True).over(run)).where("side = 1").select("event_id", "last_first_kind")


@query("join_interval", "SELECT a.event_type, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE GROUP BY 1")
def _(spark, d):
    """Events within ten minutes after another of the same user: ten-minute bins meet by equality, then the exact condition."""
    e = table(spark, d, "events").select("user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    wide = 600_000_000
    a = e.select("user_id", "event_type", "t", F.floor(F.col("t") / wide).alias("bin"))
    b = e.select("user_id", F.col("t").alias("u"), F.explode(F.array(F.floor(F.col("t") / wide), F.floor(F.col("t") / wide) - 1)).alias("bin"))
    return a.join(b, ["user_id", "bin"]).where((F.col("u") > F.col("t")) & (F.col("u") <= F.col("t") + wide)).groupBy("event_type").agg(F.count("*").alias("n"))


@query("join_theta", f"WITH r AS (SELECT l_linenumber AS m, sum({PRICE})::BIGINT AS units FROM lineitem GROUP BY 1) SELECT a.m, b.m AS n FROM r a, r b WHERE a.units < b.units OR a.m = b.m")
def _(spark, d):
    """Line numbers and those that bring more revenue, or are the same."""
    r = table(spark, d, "lineitem").groupBy(F.col("l_linenumber").alias("m")).agg(F.sum(cents("l_extendedprice")).alias("units"))
    o = r.select(F.col("m").alias("n"), F.col("units").alias("more"))
    return r.join(F.broadcast(o), (F.col("units") < F.col("more")) | (F.col("m") == F.col("n"))).select("m", "n")


# filters and aggregates
@query("filter_predicates", "SELECT p_brand, count(*) AS n FROM part WHERE p_size BETWEEN 10 AND 20 AND p_type IN (SELECT p_type FROM part WHERE p_type LIKE '%A%' OR regexp_matches(p_type, '^[E-S]')) AND p_name IS NOT NULL GROUP BY 1")
def _(spark, d):
    p = table(spark, d, "part")
    return p.where(F.col("p_size").between(10, 20) & (F.col("p_type").like("%A%") | F.col("p_type").rlike("^[E-S]")) & F.col("p_name").isNotNull()).groupBy("p_brand").agg(F.count("*").alias("n"))


@query("agg_basic", f"SELECT l_returnflag, l_linestatus, count(*) AS n, sum({PRICE})::BIGINT AS units, round(avg(l_quantity), 6) AS qty, min(l_discount) AS lo, max(l_discount) AS hi, min_by(l_shipdate, ROW(l_extendedprice, l_shipdate))::VARCHAR[1:10] AS day FROM lineitem GROUP BY 1, 2".replace("::VARCHAR[1:10]", ""))
def _(spark, d):
    li = table(spark, d, "lineitem")
    return li.groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), F.sum(cents("l_extendedprice")).alias("units"), F.round(F.avg("l_quantity"), 6).alias("qty"), F.min("l_discount").alias("lo"), F.max("l_discount").alias("hi"), F.count_if(F.col("l_tax") > 0.04).alias("taxed")
    )


SQL["agg_basic"] = f"SELECT l_returnflag, l_linestatus, count(*) AS n, sum({PRICE})::BIGINT AS units, round(avg(l_quantity), 6) AS qty, min(l_discount) AS lo, max(l_discount) AS hi, count(*) FILTER (l_tax > 0.04::DOUBLE) AS taxed FROM lineitem GROUP BY 1, 2"


@query("agg_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps, true AS near FROM lineitem")
def _(spark, d):
    r = table(spark, d, "lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("supps"), F.approx_count_distinct("l_partkey", 0.02).alias("a"))
    return r.select("parts", "supps", (F.abs(F.col("a") / F.col("parts") - 1) < 0.1).alias("near"))


_NODES = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _nodes(spark, d):
    c, n, r = (table(spark, d, t) for t in ("customer", "nation", "region"))
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))


query("agg_rollup", f"SELECT r_name, n_name, count(*) AS n {_NODES} GROUP BY ROLLUP (r_name, n_name)")(lambda s, d: _nodes(s, d).rollup("r_name", "n_name").agg(F.count("*").alias("n")))
query("agg_cube", f"SELECT r_name, c_mktsegment, count(*) AS n {_NODES} GROUP BY CUBE (r_name, c_mktsegment)")(lambda s, d: _nodes(s, d).cube("r_name", "c_mktsegment").agg(F.count("*").alias("n")))


@query("agg_gsets", "SELECT n_nationkey, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY GROUPING SETS ((n_nationkey), (c_mktsegment))")
def _(spark, d):
    views(spark, d, "customer", "nation")
    return spark.sql("SELECT n_nationkey, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY GROUPING SETS ((n_nationkey), (c_mktsegment))")


@query("agg_percentile", "SELECT event_type, round(quantile_cont(value, 0.9), 6) AS p90, round(median(value), 6) AS mid, true AS near FROM events GROUP BY 1")
def _(spark, d):
    r = table(spark, d, "events").groupBy("event_type").agg(F.percentile("value", F.lit(0.9)).alias("p"), F.median("value").alias("m"), F.percentile_approx("value", 0.9, 1000).alias("a"))
    return r.select("event_type", F.round("p", 6).alias("p90"), F.round("m", 6).alias("mid"), (F.abs(F.col("a") / F.col("p") - 1) < 0.05).alias("near"))


@query("agg_pivot", "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'O') AS \"O\", count(*) FILTER (l_linestatus = 'F') AS \"F\" FROM lineitem GROUP BY 1")
def _(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["O", "F"]).count().fillna(0)


@query("agg_unpivot", f"SELECT l_returnflag, 'n' AS name, count(*) AS v FROM lineitem GROUP BY 1 UNION ALL SELECT l_returnflag, 'units', sum({PRICE})::BIGINT FROM lineitem GROUP BY 1")
def _(spark, d):
    g = table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), F.sum(cents("l_extendedprice")).alias("units"))
    return g.unpivot("l_returnflag", ["n", "units"], "name", "v")


# windows, order, sets
@query("win_rank", """SELECT c_custkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER v, 9) AS pr, round(cume_dist() OVER v, 9) AS cd FROM customer
WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey), v AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)""")
def _(spark, d):
    w, v = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey"), Window.partitionBy("c_nationkey").orderBy("c_mktsegment")
    return table(spark, d, "customer").select(
        "c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(v), 9).alias("pr"), F.round(F.cume_dist().over(v), 9).alias("cd")
    )


@query("win_analytic", "SELECT o_orderkey, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after, first_value(o_orderkey) OVER w AS first, last_value(CASE WHEN o_orderpriority LIKE '1%' THEN o_orderkey END IGNORE NULLS) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS urgent FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def _(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    urgent = F.last(F.when(F.col("o_orderpriority").like("1%"), F.col("o_orderkey")), ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, 0))
    return table(spark, d, "orders").select("o_orderkey", F.lag("o_orderkey").over(w).alias("before"), F.lead("o_orderkey").over(w).alias("after"), F.first("o_orderkey").over(w).alias("first"), urgent.alias("urgent"))


@query("win_frames", f"SELECT o_orderkey, sum({CENTS.format('o_totalprice')}) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING)::BIGINT AS run, sum({CENTS.format('o_totalprice')}) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS three, count(*) OVER (PARTITION BY o_custkey ORDER BY date_diff('day', DATE '1990-01-01', o_orderdate::DATE) RANGE BETWEEN 90 PRECEDING AND CURRENT ROW) AS quarter FROM orders")
def _(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    r = Window.partitionBy("o_custkey").orderBy(F.datediff("o_orderdate", F.lit("1990-01-01"))).rangeBetween(-90, 0)
    c = cents("o_totalprice")
    return table(spark, d, "orders").select("o_orderkey", F.sum(c).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("run"), F.sum(c).over(w.rowsBetween(-2, 0)).alias("three"), F.count("*").over(r).alias("quarter"))


query("topk_global", f"SELECT l_orderkey, l_partkey, {PRICE} AS units FROM lineitem ORDER BY {PRICE} DESC, l_orderkey, l_partkey LIMIT 20")(
    lambda s, d: table(s, d, "lineitem").select("l_orderkey", "l_partkey", cents("l_extendedprice").alias("units")).orderBy(F.desc("units"), "l_orderkey", "l_partkey").limit(20)
)


@query("topk_group", "SELECT source, doc_id, n_chars FROM documents QUALIFY row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) <= 3")
def _(spark, d):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return table(spark, d, "documents").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("source", "doc_id", "n_chars")


_SEED = "WITH a AS (SELECT doc_id FROM documents WHERE doc_id % 3 = 0), b AS (SELECT doc_id FROM documents WHERE doc_id % 4 = 0) "


def _two(spark, d):
    t = table(spark, d, "documents").select("doc_id")
    return t.where("doc_id % 3 = 0"), t.where("doc_id % 4 = 0")


query("set_union", _SEED + "SELECT doc_id, count(*) AS n FROM (SELECT * FROM a UNION ALL SELECT * FROM b) GROUP BY 1")(lambda s, d: (lambda a, b: a.unionByName(b).groupBy("doc_id").agg(F.count("*").alias("n")))(*_two(s, d)))
query("set_union_distinct", _SEED + "SELECT * FROM a UNION SELECT * FROM b")(lambda s, d: (lambda a, b: a.union(b).distinct())(*_two(s, d)))
query("set_intersect", _SEED + "SELECT * FROM a INTERSECT SELECT * FROM b")(lambda s, d: (lambda a, b: a.intersect(b))(*_two(s, d)))
query("set_intersect_all", _SEED + "SELECT * FROM a INTERSECT ALL SELECT * FROM b")(lambda s, d: (lambda a, b: a.intersectAll(b))(*_two(s, d)))
query("set_except", _SEED + "SELECT * FROM a EXCEPT SELECT * FROM b")(lambda s, d: (lambda a, b: a.subtract(b))(*_two(s, d)))
query("set_except_all", _SEED + "SELECT * FROM a EXCEPT ALL SELECT * FROM b")(lambda s, d: (lambda a, b: a.exceptAll(b))(*_two(s, d)))


# functions
@query("fn_string", "SELECT c_custkey, upper(substr(c_name, 1, 4)) AS head, reverse(c_name) AS back, length(c_name) AS n, split_part(c_name, '#', 2) AS num, c_mktsegment || '-' || c_nationkey AS joined, md5(c_name) AS m, sha256(c_name) AS s FROM customer")
def _(spark, d):
    return table(spark, d, "customer").select(
        "c_custkey", F.upper(F.substring("c_name", 1, 4)).alias("head"), F.reverse("c_name").alias("back"), F.length("c_name").cast("bigint").alias("n"), F.split_part("c_name", F.lit("#"), F.lit(2)).alias("num"),
        F.concat_ws("-", "c_mktsegment", F.col("c_nationkey").cast("string")).alias("joined"), F.md5("c_name").alias("m"), F.sha2("c_name", 256).alias("s"),
    )


@query("fn_url_path", "SELECT page_id, list_aggregate(list_reverse(string_split(regexp_extract(url, '://([^/?#]*)', 1), '.')), 'string_agg', '.') AS host, string_split(regexp_extract(url, '://[^/?#]*/([^?#]*)', 1), '/')[1] AS first FROM pages")
def _(spark, d):
    host = F.array_join(F.reverse(F.split(F.regexp_extract("url", "://([^/?#]*)", 1), "\\.")), ".")
    return table(spark, d, "pages").select("page_id", host.alias("host"), F.get(F.split(F.regexp_extract("url", "://[^/?#]*/([^?#]*)", 1), "/"), F.lit(0)).alias("first"))


@query("fn_date", "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, day(o_orderdate)::INT AS dd, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS mm, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INT AS n, strftime(o_orderdate + INTERVAL 1 MONTH, '%Y-%m-%d') AS later, strftime(make_date(year(o_orderdate), 1, 1), '%Y-%m-%d') AS jan FROM orders")
def _(spark, d):
    day = F.col("o_orderdate")
    return table(spark, d, "orders").select(
        "o_orderkey", F.year(day).alias("y"), F.month(day).alias("m"), F.dayofmonth(day).alias("dd"), F.date_format(F.trunc(day, "month"), "yyyy-MM-dd").alias("mm"), F.datediff(day, F.lit("1995-01-01")).alias("n"),
        F.date_format(F.add_months(day, 1), "yyyy-MM-dd").alias("later"), F.date_format(F.make_date(F.year(day), F.lit(1), F.lit(1)), "yyyy-MM-dd").alias("jan"),
    )


@query("fn_math", "SELECT doc_id, least(1.0::DOUBLE, n_chars / 5000.0::DOUBLE) AS p, floor(n_chars / 7.0::DOUBLE)::BIGINT AS f, ceil(n_chars / 7.0::DOUBLE)::BIGINT AS c, round(sqrt(n_chars), 9) AS r, round(ln(n_chars + 1), 9) AS l, greatest(n_chars, 100) AS g, (n_chars % 13 + 13) % 13 AS m FROM documents")
def _(spark, d):
    n = F.col("n_chars")
    return table(spark, d, "documents").select(
        "doc_id", F.least(F.lit(1.0), n / 5000.0).alias("p"), F.floor(n / 7.0).alias("f"), F.ceil(n / 7.0).alias("c"), F.round(F.sqrt(n), 9).alias("r"), F.round(F.log(n + 1), 9).alias("l"), F.greatest(n, F.lit(100).cast("bigint")).alias("g"), F.pmod(n, F.lit(13).cast("bigint")).alias("m")
    )


@query("fn_bits", "SELECT doc_id, (doc_id << 3) AS l, (n_chars >> 2) AS r, (doc_id & 255) AS a, (doc_id | 7) AS o, xor(doc_id, n_chars) AS x, bit_count(n_chars)::INT AS b, upper(to_hex(n_chars)) AS h FROM documents")
def _(spark, d):
    return table(spark, d, "documents").select(
        "doc_id", F.shiftleft("doc_id", 3).alias("l"), F.shiftright("n_chars", 2).alias("r"), F.col("doc_id").bitwiseAND(255).alias("a"), F.col("doc_id").bitwiseOR(7).alias("o"), F.col("doc_id").bitwiseXOR(F.col("n_chars")).alias("x"), F.bit_count("n_chars").alias("b"), F.conv(F.col("n_chars").cast("string"), 10, 16).alias("h")
    )


@query("fn_array", "SELECT doc_id, list_sum(list_transform(range(0, 5), lambda i: i * (doc_id % 10)))::BIGINT AS s, len(list_filter(range(0, 12), lambda i: (doc_id >> i) % 2 = 1))::INT AS ones, list_aggregate(list_sort([doc_id % 7, doc_id % 5, doc_id % 3]), 'string_agg', ',') AS sorted, ([doc_id, doc_id + 1, doc_id + 2])[2:3]::VARCHAR AS cut FROM documents".replace(", ([doc_id, doc_id + 1, doc_id + 2])[2:3]::VARCHAR AS cut", ", list_sum(([doc_id, doc_id + 1, doc_id + 2])[2:3])::BIGINT AS cut"))
def _(spark, d):
    n = F.col("doc_id")
    return table(spark, d, "documents").select(
        "doc_id", F.aggregate(F.transform(F.sequence(F.lit(0), F.lit(4)), lambda i: i * (n % 10)), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("s"),
        F.size(F.filter(F.sequence(F.lit(0), F.lit(11)), lambda i: F.call_function("shiftright", n, i) % 2 == 1)).alias("ones"),
        F.array_join(F.array_sort(F.array(n % 7, n % 5, n % 3)), ",").alias("sorted"), F.aggregate(F.slice(F.array(n, n + 1, n + 2), 2, 2), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("cut"),
    )


@query("fn_vector", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS norm, round(embedding[1]::DOUBLE, 6) AS first, round(list_sum(list_transform(list_zip(embedding, list_reverse(embedding)), lambda z: z[1]::DOUBLE * z[2]::DOUBLE)), 6) AS mirror FROM embeddings")
def _(spark, d):
    v = F.transform("embedding", lambda x: x.cast("double"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    return table(spark, d, "embeddings").select("vec_id", F.round(dot(v, v), 6).alias("norm"), F.round(F.get(v, F.lit(0)), 6).alias("first"), F.round(dot(v, F.reverse(v)), 6).alias("mirror"))


@query("fn_map_struct", "SELECT l_returnflag, count(*) AS kinds, max(n) AS most, min(ROW(n, l_linestatus)).n AS least_n FROM (SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY 1, 2) GROUP BY 1".replace("min(ROW(n, l_linestatus)).n", "min(n)"))
def _(spark, d):
    g = table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))
    m = g.groupBy("l_returnflag").agg(F.map_from_entries(F.collect_list(F.struct("l_linestatus", "n"))).alias("m"), F.min(F.struct("n", "l_linestatus")).alias("least"))
    return m.select("l_returnflag", F.size("m").cast("bigint").alias("kinds"), F.array_max(F.map_values(F.map_filter("m", lambda k, v: v > 0))).alias("most"), F.col("least.n").alias("least_n"))


@query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k, CAST(json_extract_string(props, '$.k') AS INT) AS parsed FROM events")
def _(spark, d):
    return table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.from_json(F.to_json(F.from_json("props", "k int")), "k int")["k"].alias("parsed"))


@query("fn_cond", "SELECT doc_id, coalesce(quality, -1)::INT AS q, nullif(toxic, 0) AS t, CASE WHEN quality = 1 THEN 'good' WHEN quality = 0 THEN 'bad' ELSE 'none' END AS c FROM documents LEFT JOIN labels USING (doc_id)")
def _(spark, d):
    r = table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels"), "doc_id", "left")
    return r.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("q"), F.nullif("toxic", F.lit(0)).alias("t"), F.when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "bad").otherwise("none").alias("c"))


@query("fn_decimal", f"SELECT sum({PRICE}::DECIMAL(38,0))::VARCHAR AS whole, count(TRY_CAST(l_returnflag AS INT)) AS numbers FROM lineitem")
def _(spark, d):
    return table(spark, d, "lineitem").agg(F.sum(cents("l_extendedprice").cast("decimal(38,0)")).cast("decimal(38,0)").cast("string").alias("whole"), F.count(F.col("l_returnflag").try_cast("int")).alias("numbers"))


# SQL over a summary
@query("sql_subquery", DOCS + ", g AS (SELECT source, sum(adj_weight) AS e FROM smp GROUP BY 1) SELECT source FROM g WHERE e > (SELECT avg(e) FROM g) AND EXISTS (SELECT 1 FROM smp WHERE smp.source = g.source AND is_heavy)")
def _(spark, d):
    docs_summary(spark, d).rows.createOrReplaceTempView("smp")
    return spark.sql("WITH g AS (SELECT source, sum(adj_weight) AS e FROM smp GROUP BY 1) SELECT source FROM g WHERE e > (SELECT avg(e) FROM g) AND EXISTS (SELECT 1 FROM smp WHERE smp.source = g.source AND is_heavy)")


@query("sql_estimate", DOCS + " SELECT lang, round(sum(adj_weight), 2) AS est FROM smp GROUP BY 1")
def _(spark, d):
    """Estimates in SQL: a view of the summary and a SQL function for the adjusted weight."""
    out = docs_summary(spark, d)
    out.rows.createOrReplaceTempView("summary_v")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION adjusted(units BIGINT, tau DOUBLE) RETURNS DOUBLE RETURN greatest(CAST(units AS DOUBLE), tau)")
    return spark.sql(f"SELECT lang, round(sum(adjusted(units, {out.th.tau!r}D)), 2) AS est FROM summary_v GROUP BY lang")


# windows of time, on the batch
@query("win_tumbling", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def _(spark, d):
    return table(spark, d, "events").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@query("win_sliding", "WITH e AS (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS h FROM events) SELECT strftime(h, '%Y-%m-%d %H') AS start, count(*) AS n FROM e GROUP BY 1")
def _(spark, d):
    return table(spark, d, "events").groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH").alias("start"), "n")


@query("win_session", "WITH e AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, count(DISTINCT k) AS sessions FROM s GROUP BY 1")
def _(spark, d):
    s = table(spark, d, "events").groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n"))
    return s.groupBy("user_id").agg(F.count("*").alias("sessions"))


# functions in Python
@query("udf_interval", bounds_sql(0.99) + " SELECT lang, n_light, lo, hi FROM bounds")
def _(spark, d):
    from rangekeep.operators import estimate as E

    out = docs_summary(spark, d)
    r = E.with_bounds(E.split_counts(out, "lang"), out.th.tau, 0.99)
    return r.select("lang", "n_light", *[F.round(c, 2).alias(c) for c in ("lo", "hi")])


@query("udaf_tau", "WITH t AS (SELECT source, n_chars AS w, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) - 1 AS k, count(*) OVER (PARTITION BY source) AS n, sum(n_chars) OVER (PARTITION BY source)::DOUBLE AS t, sum(n_chars) OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id ROWS UNBOUNDED PRECEDING) - n_chars AS h FROM documents), l AS (SELECT source, min(ROW(k, (t - h) / (5 - k))) AS m FROM t WHERE n > 5 AND k < 5 AND w * (5 - k) < t - h GROUP BY 1) SELECT source, round(m[2]::DOUBLE, 6) AS tau FROM l".replace("min(ROW(k, (t - h) / (5 - k))) AS m", "arg_min((t - h) / (5 - k), k) AS m").replace("m[2]::DOUBLE", "m"))
def _(spark, d):
    """The threshold of each source for five keys, as a grouped aggregate in Python; groups are small."""
    from rangekeep.operators.ipps import local_threshold

    @F.pandas_udf("double")
    def tau(w: pd.Series) -> float:
        return float(local_threshold(w.to_numpy(float), float(w.sum()), 5)) if len(w) > 5 else 0.0

    return table(spark, d, "documents").groupBy("source").agg(tau("n_chars").alias("t")).where("t > 0").select("source", F.round("t", 6).alias("tau"))


@query("udtf_dyadic", """WITH spans AS (SELECT date_diff('day', DATE '1990-01-01', l_shipdate::DATE)::INT AS day, min(l_partkey)::BIGINT AS lo, max(l_partkey)::BIGINT + 1 AS hi FROM lineitem GROUP BY 1)
SELECT day, l, k FROM spans, (SELECT unnest(range(33))::INT AS l), LATERAL (SELECT DISTINCT unnest([(lo + (1::BIGINT << l) - 1) >> l, (hi >> l) - 1]) AS k)
WHERE k >= 0 AND k << l >= lo AND (k + 1) << l <= hi AND NOT (l < 32 AND (k >> 1) << (l + 1) >= lo AND ((k >> 1) + 1) << (l + 1) <= hi)""")
def _(spark, d):
    """Dyadic pieces of each shipping day's stretch of parts by a table function."""
    from rangekeep.functions.tables import DyadicCover

    spark.udtf.register("dyadic_cover", DyadicCover)
    side = [F.min("l_partkey").cast("bigint").alias("lo"), (F.max("l_partkey").cast("bigint") + 1).alias("hi")]
    table(spark, d, "lineitem").groupBy(F.datediff("l_shipdate", F.lit("1990-01-01")).alias("day")).agg(*side).createOrReplaceTempView("dyadic_spans")
    return spark.sql("SELECT day, l, k FROM dyadic_spans, LATERAL dyadic_cover(lo, hi, 32)")


# Spark's own samplers, for comparison: their draws are not DuckDB's, so rows only
query("sample_builtin")(lambda s, d: table(s, d, "documents").select("doc_id").sample(0.3, seed=1))
query("sample_by")(lambda s, d: table(s, d, "documents").select("doc_id", "lang").sampleBy("lang", {"en": 0.2, "fr": 0.5}, seed=1))


@query("sample_table")
def _(spark, d):
    views(spark, d, "documents")
    return spark.sql("SELECT doc_id FROM documents TABLESAMPLE (30 PERCENT) REPEATABLE (1)")


@query("overlap_of_seeds", "SELECT least(300, count(*))::BIGINT AS a, least(300, count(*))::BIGINT AS b, true AS shares_heavy FROM documents WHERE n_chars > 0")
def _(spark, d):
    """Two seeds' samples share at least the heavy keys."""
    from rangekeep.plans.sampling_queries import key_set

    k = key_set(spark, d, "docs")
    a, b = (keep(S.varopt(k, 300, seed=i).rows.select("hk", "is_heavy")) for i in (1, 2))
    both = a.select("hk").intersect(b.select("hk")).count()
    return spark.createDataFrame([(a.count(), b.count(), both >= a.where("is_heavy").count())], "a bigint, b bigint, shares_heavy boolean")


def queries():
    return dict(QUERIES)


def oracle_sql():
    return dict(SQL)
