"""Line dedup: drop lines that many documents share, keeping each in one of them.

Texts are split at \\n (null or empty: one empty line). A line's key is the line without ASCII blanks at both ends,
A-Z lower-cased. Keys of at least `least_chars` code points found in at least `least_docs` different ids lose all
their lines except those of the largest id that holds them. Documents are told apart by id: repeated rows with one id
count once and are treated alike. Rows with a null id neither count nor lose lines. Extra columns stay; those named
like a result are replaced. An empty table gives an empty result.

Shape: lines become (128-bit hash, id) pairs, made distinct before they are counted, so a line held by a third of all
documents is folded map-side; only positions of doomed lines travel back to the documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rangekeep.llm._shared import keep, lower_az, small

LEAST_CHARS, LEAST_DOCS = 20, 3


def lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def key(line: Column) -> Column:
    return lower_az(F.btrim(line, F.lit(" \t\n\x0b\f\r")))


def drop_shared_lines(docs: DataFrame, text: str = "text", key_col: str = "doc_id", least_chars: int = LEAST_CHARS, least_docs: int = LEAST_DOCS) -> DataFrame:
    """docs with text without its shared lines, and n_lines, n_dropped."""
    held = docs.select(F.col(key_col).alias("__id"), F.posexplode(lines(F.col(text))).alias("__at", "__line")).where(F.col("__id").isNotNull())
    held = held.withColumn("__key", key(F.col("__line"))).where(F.length("__key") >= least_chars)
    held = held.select("__id", "__at", F.xxhash64("__key").alias("__h1"), F.xxhash64(F.lit("again"), "__key").alias("__h2"))
    shared = keep(
        held.groupBy("__h1", "__h2", "__id").agg(F.lit(1).alias("one"))
        .groupBy("__h1", "__h2").agg(F.count("*").alias("n"), F.max("__id").alias("__stays"))
        .where(F.col("n") >= least_docs).select("__h1", "__h2", "__stays")
    )
    doomed = (
        held.join(small(shared), ["__h1", "__h2"]).where(F.col("__id") != F.col("__stays"))
        .groupBy(F.col("__id").alias("__doc")).agg(F.collect_set("__at").alias("__doomed"))
    )
    kept = [c for c in docs.columns if c not in (text, "n_lines", "n_dropped")]
    out = docs.select(*kept, lines(F.col(text)).alias("__lines")).join(doomed, F.col(key_col) == F.col("__doc"), "left")
    places = F.sequence(F.lit(0), F.size("__lines") - 1)
    left = F.when(F.col("__doomed").isNull(), F.col("__lines")).otherwise(
        F.transform(F.array_except(places, F.col("__doomed")), lambda i: F.element_at(F.col("__lines"), i + 1))
    )
    out = out.select(
        *kept, F.array_join(left, "\n").alias(text), F.size("__lines").cast("long").alias("n_lines"),
        F.coalesce(F.size("__doomed"), F.lit(0)).cast("long").alias("n_dropped"), "__doomed",
    )
    out = out.withColumn("n_dropped", F.when(F.col("__doomed").isNull(), F.lit(0)).otherwise(F.col("n_dropped")).cast("long")).drop("__doomed")
    return out.select(*[c for c in docs.columns if c not in ("n_lines", "n_dropped")], "n_lines", "n_dropped")


def query(spark, sf_dir: str) -> DataFrame:
    from rangekeep.llm._shared import table

    out = drop_shared_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2("text", 256).alias("kept_sha256"))


SQL = """
WITH d AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
l AS (SELECT doc_id, unnest(ls) AS line, generate_subscripts(ls, 1) AS pos FROM d),
k AS (SELECT doc_id, pos, line, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
      'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
s AS (SELECT key, max(doc_id) AS stays FROM k WHERE length(key) >= 20 GROUP BY key HAVING count(DISTINCT doc_id) >= 3),
m AS (SELECT k.doc_id, k.pos, k.line, s.key IS NOT NULL AND k.doc_id <> s.stays AS gone FROM k LEFT JOIN s ON k.key = s.key)
SELECT doc_id, count(*)::BIGINT AS n_lines, (count(*) FILTER (gone))::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS kept_sha256
FROM m GROUP BY doc_id
"""
