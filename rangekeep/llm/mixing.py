"""Mixing sources to target weights by Pareto order sampling, in DataFrame functions only.

A document's size is its number of words. Sources, ordered by code point with null last, weigh 5, 2, 1, repeating, and
share 150 % of all sizes; a target stops at twice its source's size and what is over is shared again by weight, which
ends at the level L where the targets min(2 size, L weight) add up to the whole. With r = target / source size, every
document gets floor(r) certain copies; the words still missing come from a Pareto order sample of one more copy.

Inclusion probabilities are unequal: p is c times the number of bits of the document's size, so that longer documents
are likelier, and at most 1; c makes the expected words of a source what it misses. Documents of p = 1 are certain. The
others rank by their random odds u/(1-u) divided by their inclusion odds p/(1-p), and the first ones are taken until
their words reach what is missing (the last only if its middle lies below that). u comes from the document's id, so that reruns agree.

Sources of size zero get target 0; empty documents take 0 words. Repeated rows share one draw and are ordered by
nothing else, so that both are taken or the tie is cut at the target. Extra columns stay. Nulls: text counts as empty, source is a source of its own.

Shape: sizes are kept once in a narrow table (source, size, u) and folded per source and class of sizes, then per
source and cell of ranks (`CELLS` cells), before any exchange; running sums need one small table of cells and a window
inside each cell, never one over a whole source.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangekeep.llm._shared import keep, n_words, small

WEIGHTS = (5, 2, 1)
SHARE = 1.5
MOST = 2
CELLS = 1 << 12


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """From (source, source_size), a row per source: source, source_size, target. As many rows as there are sources."""
    order = Window.orderBy(F.col("source").isNull(), F.col("source").cast("binary"))
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int"))
    rows = sizes.withColumn("w", w).withColumn("cap", (most * F.col("source_size")).cast("double"))
    # by rising cap / weight, the sources before the first that the common level does not fill are full
    fill = Window.orderBy(F.col("cap") / F.col("w"), F.col("source").isNull(), F.col("source").cast("binary"))
    before, rest = fill.rowsBetween(Window.unboundedPreceding, -1), fill.rowsBetween(0, Window.unboundedFollowing)
    whole = F.sum("source_size").over(Window.partitionBy()) * F.lit(float(share))
    rows = rows.withColumn("level", (whole - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("w").over(rest))
    rows = rows.withColumn("free", F.col("level") * F.col("w") < F.col("cap"))
    # treating a free source as full only lowers the level, so the first free one has the largest
    level = F.max(F.when(F.col("free"), F.col("level"))).over(Window.partitionBy())
    return rows.select("source", "source_size", F.when(level.isNull(), F.col("cap")).otherwise(F.least(F.col("cap"), level * F.col("w"))).alias("target"))


def bits(size: Column) -> Column:
    """Number of binary digits of a size; 0 for 0."""
    return F.when(size > 0, F.length(F.bin(size))).otherwise(0).cast("long")


def inclusion(classes: DataFrame, aims: DataFrame) -> DataFrame:
    """From (source, class, words) and (source, source_size, target): source, class, whole, p, and `left`, the words of a
    source that its documents of p < 1 are to bring. p = min(1, c class), with c so that the sum of p words is what whole
    copies leave missing; a source has one class for each binary digit of its longest document at most."""
    rows = classes.join(F.broadcast(aims) if aims.count() <= 100_000 else aims, classes["source"].eqNullSafe(aims["source"])).select(classes["source"], "class", "words", "source_size", "target")
    rows = rows.withColumn("whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long"))
    rows = rows.withColumn("missing", F.col("target") - F.col("whole") * F.col("source_size"))
    fall = Window.partitionBy("source").orderBy(F.desc("class"))
    rows = rows.withColumn("certain", F.coalesce(F.sum("words").over(fall.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    pull = F.sum(F.col("words") * F.col("class")).over(fall.rowsBetween(0, Window.unboundedFollowing))
    rows = rows.withColumn("c", F.when(pull > 0, (F.col("missing") - F.col("certain")) / pull))
    # taking a class that has p < 1 as certain only lowers c, so the first one that is not certain has the largest
    free = F.when((F.col("c") * F.col("class") < 1) & (F.col("c") > 0), F.struct("c", "certain"))
    rows = rows.withColumn("best", F.max(free).over(Window.partitionBy("source")))
    p = F.when(F.col("missing") <= 0, 0.0).when(F.col("best").isNull(), 1.0).otherwise(F.least(F.lit(1.0), F.col("best.c") * F.col("class")))
    sure = F.sum(F.when(p >= 1, F.col("words")).otherwise(0)).over(Window.partitionBy("source"))
    return rows.select("source", "class", "whole", p.alias("p"), (F.col("missing") - sure).alias("left"), "source_size", "target")


def rank(u: Column, p: Column) -> Column:
    """Random odds over inclusion odds; null where a document is certain or can't be taken."""
    return F.when((p > 0) & (p < 1), (u / (1 - u)) / (p / (1 - p)))


def mix(docs: DataFrame, text: str = "text", source: str = "source", key: str = "doc_id", seed: str = "mix", rising=bits, **how) -> DataFrame:
    """docs with size, source_size, target, copies and taken. rising(size) gives the class that p is proportional to."""
    plain = [c for c in docs.columns if c not in ("size", "source_size", "target", "copies", "taken")]
    digits = F.substring(F.md5(F.concat_ws("|", F.lit(seed), F.coalesce(F.col(key).cast("string"), F.lit("null")))), 1, 12)
    u = (F.conv(digits, 16, 10).cast("long") + 0.5) / float(1 << 48)
    sized = docs.select(*plain, F.col(source).alias("__s"), n_words(F.col(text)).alias("size"), u.alias("__u"))
    narrow = keep(sized.select(F.col("__s").alias("source"), "size", F.col("__u").alias("u")))
    classes = keep(narrow.groupBy("source", rising(F.col("size")).alias("class")).agg(F.sum("size").alias("words")))
    aims = keep(targets(classes.groupBy("source").agg(F.sum("words").alias("source_size")), **how))
    odds = keep(inclusion(classes, aims)).select(F.col("source").alias("__source"), F.col("class").alias("__class"), "whole", "p", "left", "source_size", "target")
    q = rank(F.col("u"), F.col("p"))
    cell = lambda q: F.floor(q / (1 + q) * CELLS).cast("int")
    met = F.col("source").eqNullSafe(F.col("__source")) & (rising(F.col("size")) == F.col("__class"))
    cells = narrow.join(small(odds), met).where(q.isNotNull()).groupBy("source", cell(q).alias("cell")).agg(F.sum("size").alias("cell_size"))
    # words before each document in the order of its source: those of earlier cells, then those in its cell
    run = Window.partitionBy("source").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    starts = keep(cells.select(F.col("source").alias("__from"), F.col("cell").alias("__at"), F.coalesce(F.sum("cell_size").over(run), F.lit(0)).alias("__start")))
    rows = sized.join(small(odds), F.col("__s").eqNullSafe(F.col("__source")) & (rising(F.col("size")) == F.col("__class"))).drop("__source", "__class")
    rows = rows.withColumn("__q", rank(F.col("__u"), F.col("p"))).withColumn("__cell", cell(F.col("__q")))
    rows = rows.join(small(starts), F.col("__s").eqNullSafe(F.col("__from")) & (F.col("__cell") == F.col("__at")), "left").drop("__from", "__at")
    inside = Window.partitionBy("__s", "__cell", F.when(F.col("__cell").isNull(), F.spark_partition_id())).orderBy("__q", "__u", F.col(key)).rowsBetween(Window.unboundedPreceding, -1)
    before = F.col("__start") + F.coalesce(F.sum("size").over(inside), F.lit(0))
    more = (F.col("p") >= 1) | (F.col("__q").isNotNull() & (before + F.col("size") / 2 <= F.col("left")))
    rows = rows.withColumn("copies", (F.col("whole") + F.coalesce(more, F.lit(False)).cast("long")).cast("long"))
    return rows.select(*plain, "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def query(spark, sf_dir: str) -> DataFrame:
    from rangekeep.llm._shared import table

    return mix(table(spark, sf_dir, "documents").select("doc_id", "text", "source")).select("doc_id", "size", "source_size", "target", "taken")


SQL = """
WITH d AS (SELECT doc_id, source, length(regexp_replace(regexp_replace(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+', 'w', 'g'), '[\\x20\\x09-\\x0D]', '', 'g'))::BIGINT AS size,
  ((('0x' || substr(md5('mix|' || coalesce(doc_id::VARCHAR, 'null')), 1, 12))::BIGINT) + 0.5) / 281474976710656.0::DOUBLE AS u FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, [5.0::DOUBLE, 2.0::DOUBLE, 1.0::DOUBLE][((row_number() OVER (ORDER BY source IS NULL, encode(source)) - 1) % 3 + 1)::INT] AS w, 2.0::DOUBLE * source_size AS cap FROM s),
l AS (SELECT *, ((SELECT sum(source_size) FROM s)::DOUBLE * 1.5::DOUBLE - coalesce(sum(cap) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) /
  sum(w) OVER (o ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS lev FROM w WINDOW o AS (ORDER BY cap / w, source IS NULL, encode(source))),
t AS (SELECT source, source_size, coalesce(least(cap, (SELECT max(lev) FROM l WHERE lev * w < cap) * w), cap) AS target FROM l),
r AS (SELECT *, CASE WHEN source_size > 0 THEN target / source_size ELSE 0.0 END AS ratio FROM t),
k AS (SELECT source, CASE WHEN size > 0 THEN length(bin(size)) ELSE 0 END AS class, sum(size)::BIGINT AS words FROM d GROUP BY 1, 2),
m AS (SELECT k.*, r.source_size, r.target, floor(r.ratio)::BIGINT AS whole, r.target - floor(r.ratio)::BIGINT * r.source_size AS missing FROM k JOIN r ON k.source IS NOT DISTINCT FROM r.source),
n AS (SELECT *, coalesce(sum(words) OVER (PARTITION BY source ORDER BY class DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS certain,
  sum(words * class) OVER (PARTITION BY source ORDER BY class DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)::BIGINT AS pull FROM m),
o AS (SELECT *, CASE WHEN pull > 0 THEN (missing - certain) / pull::DOUBLE END AS c FROM n),
e AS (SELECT *, max(CASE WHEN c * class < 1 AND c > 0 THEN c END) OVER (PARTITION BY source) AS best FROM o),
f AS (SELECT *, CASE WHEN missing <= 0 THEN 0.0::DOUBLE WHEN best IS NULL THEN 1.0::DOUBLE ELSE least(1.0::DOUBLE, best * class) END AS p FROM e),
g AS (SELECT *, missing - (sum(CASE WHEN p >= 1 THEN words ELSE 0 END) OVER (PARTITION BY source))::BIGINT AS room FROM f),
j AS (SELECT d.doc_id, d.size, d.u, d.source, g.source_size, g.target, g.whole, g.p, g.room,
  CASE WHEN p > 0 AND p < 1 THEN (u / (1 - u)) / (p / (1 - p)) END AS q FROM d JOIN g ON d.source IS NOT DISTINCT FROM g.source AND g.class = CASE WHEN d.size > 0 THEN length(bin(d.size)) ELSE 0 END),
b AS (SELECT *, coalesce(sum(size) OVER (PARTITION BY source, q IS NULL ORDER BY floor(q / (1 + q) * 4096), q, u, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM j)
SELECT doc_id, size, source_size, target, (whole + CASE WHEN p >= 1 OR (q IS NOT NULL AND before + size / 2.0::DOUBLE <= room) THEN 1 ELSE 0 END)::BIGINT * size AS taken
FROM b
"""
