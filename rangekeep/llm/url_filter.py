"""URL filter: host rules first, then association rules mined from labels by FP-growth.

Given rules (host, path) say allow or block: a rule fits its host and all subdomains if the url's path starts with the
rule's, and the longest fitting rule wins. Where none fits the method decides: FP-growth mines rules tokens -> label from
the labelled urls' tokens; those under the least support or confidence, and those that a shorter rule with no
lower confidence already implies, go; the rest are matched through an inverted index from token to rules. A url is
blocked if the most confident rule that fires says block, else allowed.

FP-growth over whole token sets would list every subset of a frequent set, 2^k for a url of k tokens that many share.
So combinations grow level by level up to `most_tokens`, and a basket holds one combination and its label: FP-growth
counts, prunes by support and gives the confidence. Two facts keep the levels small and lose no rule. A combination
that meets one label only is certain, and all that hold more tokens are implied by it. Tokens that stand in the very same
labelled urls are one: a rule needs any of them. Support is a share of the labelled urls and never fewer than `least_rows`.

A null url or one without :// has an empty host and path, no rule, no token but an empty one, and is allowed unless
labels say otherwise. Repeated rows are judged each alike; extra columns are left out but for `columns`; an empty table, or one
without both labels, mines no rule and allows what no given rule blocks.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rangekeep.llm._shared import keep, lower_az, small

#: (verdict, host, path)
RULES = (("allow", "com", "/"), ("block", "example.com", "/en/"), ("allow", "www.example.com", "/en/"), ("block", "net", "/es/"), ("block", "net", "/fr/"))
LEAST_SUPPORT, LEAST_CONFIDENCE, LEAST_ROWS = 0.002, 0.6, 3
#: Tokens that a rule may need.
MOST_TOKENS = 4


def host(url: Column) -> Column:
    rest = F.regexp_extract(F.coalesce(url, F.lit("")), "^[\\s\\S]*?://([\\s\\S]*)$", 1)
    return lower_az(F.regexp_extract(rest, "^([^/?#]*)", 1))


def path(url: Column) -> Column:
    rest = F.regexp_extract(F.coalesce(url, F.lit("")), "^[\\s\\S]*?://([\\s\\S]*)$", 1)
    return F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1)


def given(h: Column, p: Column, rules=RULES) -> Column:
    """Struct (rule, verdict) of the longest given rule that fits; null if none does."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for verdict, rh, rp in sorted(rules, key=lambda r: (len(r[1] + r[2]), r)):
        fits = ((h == rh) | h.endswith("." + rh)) & p.startswith(rp)
        out = F.when(fits, F.struct(F.lit(rh + rp).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def tokens(h: Column, p: Column, url: Column) -> Column:
    """Distinct tokens: host labels with the last one's rank, words inside labels, path parts with digits folded, query keys."""
    label = F.transform(F.filter(F.split(h, "\\."), lambda x: x != ""), lambda x: F.concat(F.lit("h:"), x))
    inner = F.transform(F.filter(F.split(h, "[.-]"), lambda x: x != ""), lambda x: F.concat(F.lit("w:"), F.regexp_replace(x, "[0-9]+", "0")))
    last = F.array(F.concat(F.lit("t:"), F.substring_index(h, ".", -1)))
    part = F.transform(F.filter(F.split(p, "/"), lambda x: x != ""), lambda x: F.concat(F.lit("p:"), F.regexp_replace(x, "[0-9]+", "0")))
    keys = F.transform(F.regexp_extract_all(F.coalesce(url, F.lit("")), F.lit("[?&]([^=&#]+)"), F.lit(1)), lambda x: F.concat(F.lit("q:"), x))
    return F.array_distinct(F.concat(label, inner, last, part, keys))


@dataclass(frozen=True)
class Rules:
    """Tables: rules (rule, need, verdict, confidence) from the best down, and names (token, class) of what they need."""

    rules: DataFrame
    names: DataFrame


def _grown(labelled: DataFrame, least: int) -> tuple[DataFrame, DataFrame]:
    """(names (token, class) of frequent tokens, folded rows (row, classes, verdict, n)).

    Equal rows are folded to one with their number. Tokens of the same rows have equal counts and equal sums of the rows' hashes.
    """
    folded = labelled.groupBy(F.array_sort(F.array_distinct("tokens")).alias("tokens"), "verdict").agg(F.count("*").alias("n"))
    folded = keep(folded.withColumns({"row": F.xxhash64("tokens", "verdict"), "again": F.xxhash64(F.lit("again"), "verdict", "tokens")}))
    each = folded.select("row", "again", "verdict", "n", F.explode("tokens").alias("token"))
    part = lambda c: F.sum(F.pmod(F.col(c), F.lit((1 << 31) - 1)).cast("decimal(38,0)"))
    marks = each.groupBy("token").agg(F.sum("n").alias("rows"), part("row").alias("a"), part("again").alias("b")).where(F.col("rows") >= least)
    first = marks.withColumn("first", F.min("token").over(Window.partitionBy("rows", "a", "b")))
    # as many frequent tokens as the support allows, whatever the number of rows
    names = keep(first.select("token", (F.dense_rank().over(Window.orderBy(F.col("first").cast("binary"))) - 1).cast("int").alias("class")))
    held = each.join(small(names), "token").groupBy("row", "again").agg(F.array_sort(F.collect_set("class")).alias("classes"), F.first("verdict").alias("verdict"), F.first("n").alias("n"))
    return names, keep(held)


def _counted(level: DataFrame, least: int, least_confidence: float) -> tuple[DataFrame, DataFrame]:
    """FP-growth over baskets of one combination and its label: (rules (set, verdict, confidence), sets worth more tokens)."""
    baskets = level.select(F.array(F.concat(F.lit("+"), F.concat_ws(" ", "set")), F.concat(F.lit("="), F.col("verdict"))).alias("items"), F.explode(F.sequence(F.lit(1), F.col("n").cast("int"))).alias("i"))
    baskets = keep(baskets.select("items"))
    many = baskets.count()
    fitted = FPGrowth(itemsCol="items", minSupport=min(1.0, (least - 0.5) / max(1, many)), minConfidence=least_confidence).fit(baskets)
    # fewer baskets than a rule needs hold none
    is_set = lambda c: F.lit(many >= least) & F.get(c, F.lit(0)).startswith("+")
    numbers = lambda c: F.split(F.substr(c, F.lit(2)), " ").cast("array<int>")
    found = fitted.associationRules.where(is_set("antecedent"))
    rules = keep(found.select(numbers(F.get("antecedent", F.lit(0))).alias("set"), F.substr(F.get("consequent", F.lit(0)), F.lit(2)).alias("verdict"), "confidence"))
    # a set is worth more tokens if some label is frequent with it and not its only one
    sets = fitted.freqItemsets
    alone = sets.where((F.size("items") == 1) & is_set("items")).select(F.get("items", F.lit(0)).alias("x"), F.col("freq").alias("all"))
    both = sets.where(F.size("items") == 2).select(F.array_min("items").alias("x"), F.col("freq").alias("some"))
    more = both.join(alone, "x").where(F.col("some") < F.col("all")).select(numbers(F.col("x")).alias("set")).distinct()
    return rules, keep(more)


def mine(labelled: DataFrame, least_support: float = LEAST_SUPPORT, least_confidence: float = LEAST_CONFIDENCE, most_tokens: int = MOST_TOKENS, least_rows: int = LEAST_ROWS) -> Rules | None:
    """Rules from rows (tokens, verdict); None where there are not two labels.

    A rule's rows with its verdict number at least max(least_rows, least_support of all rows).
    """
    facts = labelled.agg(F.count("*").alias("n"), F.min("verdict").alias("a"), F.max("verdict").alias("b")).first()
    if not facts.n or facts.a == facts.b:
        return None
    least = max(1, least_rows, math.ceil(least_support * facts.n - 1e-9))
    names, rows = _grown(labelled, least)
    level = rows.select("classes", F.posexplode("classes").alias("at", "class"), "verdict", "n").select("classes", F.array("class").alias("set"), "at", "verdict", "n")
    every = None
    for size in range(1, most_tokens + 1):
        level = keep(level)
        rules, more = _counted(level, least, least_confidence)
        every = rules if every is None else every.unionByName(rules)
        if size == 1:
            # from here on a row's classes are those that are worth more
            ok = more.select(F.get("set", F.lit(0)).alias("c"))
            left = rows.select("row", "again", "verdict", "n", F.explode("classes").alias("c")).join(small(ok), "c", "left_semi")
            left = left.groupBy("row", "again").agg(F.array_sort(F.collect_set("c")).alias("classes"), F.first("verdict").alias("verdict"), F.first("n").alias("n"))
            level = left.select("classes", F.posexplode("classes").alias("at", "class"), "verdict", "n").select("classes", F.array("class").alias("set"), "at", "verdict", "n")
        else:
            level = level.join(small(more), "set", "left_semi")
        nexts = F.posexplode(F.slice("classes", F.col("at") + 2, F.size("classes")))
        level = level.select("classes", "set", F.col("at").alias("was"), "verdict", "n", nexts.alias("step", "class"))
        level = level.select("classes", F.concat("set", F.array("class")).alias("set"), (F.col("was") + 1 + F.col("step")).alias("at"), "verdict", "n")
    every = keep(every)
    # a rule is implied if dropping one token leaves a rule at least as confident
    shorter = every.select(F.col("set").alias("rest"), "verdict", F.col("confidence").alias("had"))
    drops = every.where(F.size("set") > 1).select("set", "verdict", "confidence", F.explode("set").alias("t"))
    drops = drops.select("set", "verdict", "confidence", F.array_remove("set", F.col("t")).alias("rest"))
    implied = drops.join(shorter, ["rest", "verdict"]).where(F.col("had") >= F.col("confidence")).select("set", "verdict").distinct()
    best = Window.orderBy(F.desc("confidence"), F.size("set"), "set", "verdict")
    kept = every.join(implied, ["set", "verdict"], "left_anti").select((F.row_number().over(best) - 1).alias("rule"), F.col("set").alias("need"), "verdict", "confidence")
    return Rules(keep(kept), names)


def fires(sets: DataFrame, mined: Rules) -> DataFrame:
    """(key..., verdict) of rows (k1, k2, tokens): that of the best rule whose needs are all met; rows where none is are left out."""
    index = mined.rules.select("rule", F.col("verdict").alias("says"), F.size("need").alias("many"), F.explode("need").alias("class"))
    has = sets.select("k1", "k2", F.explode("tokens").alias("token")).join(small(mined.names), "token").select("k1", "k2", "class").distinct()
    hit = has.join(small(index), "class").groupBy("k1", "k2", "rule").agg(F.count("*").alias("met"), F.first("many").alias("many"), F.first("says").alias("says"))
    return hit.where("met = many").groupBy("k1", "k2").agg(F.min_by("says", "rule").alias("verdict"))


def judge(pages: DataFrame, url: str = "url", columns: tuple[str, ...] = ("page_id",), rules=RULES, labels: DataFrame | None = None, **how) -> DataFrame:
    """columns, host, path, rule, verdict. labels (url, verdict) default to the urls that a given rule settles."""
    rows = pages.select(*columns, F.col(url).alias("__url"), host(F.col(url)).alias("host"), path(F.col(url)).alias("path"))
    rows = rows.withColumn("__given", given(F.col("host"), F.col("path"), rules))
    if labels is None:
        known = rows.where(F.col("__given").isNotNull()).select(tokens(F.col("host"), F.col("path"), F.col("__url")).alias("tokens"), F.col("__given.verdict").alias("verdict"))
    else:
        known = labels.where(F.col("verdict").isNotNull()).select(tokens(host(F.col("url")), path(F.col("url")), F.col("url")).alias("tokens"), "verdict")
    mined = mine(known, **how)
    out = [*columns, "host", "path", F.col("__given.rule").alias("rule")]
    if mined is None:
        return rows.select(*out, F.coalesce(F.col("__given.verdict"), F.lit("allow")).alias("verdict"))
    rows = rows.withColumn("__tokens", F.when(F.col("__given").isNull(), F.array_sort(tokens(F.col("host"), F.col("path"), F.col("__url")))))
    rows = rows.withColumns({"__1": F.xxhash64("__tokens"), "__2": F.xxhash64(F.lit("again"), "__tokens")}).drop("__url")
    # equal token sets are judged once
    sets = rows.where(F.col("__tokens").isNotNull()).groupBy(F.col("__1").alias("k1"), F.col("__2").alias("k2")).agg(F.first("__tokens").alias("tokens"))
    verdicts = keep(fires(sets, mined)).select(F.col("k1").alias("__k1"), F.col("k2").alias("__k2"), F.col("verdict").alias("__says"))
    met = F.col("__tokens").isNotNull() & (F.col("__1") == F.col("__k1")) & (F.col("__2") == F.col("__k2"))
    rows = rows.join(small(verdicts), met, "left")
    return rows.select(*out, F.coalesce(F.col("__given.verdict"), F.col("__says"), F.lit("allow")).alias("verdict"))


def query(spark, sf_dir: str) -> DataFrame:
    from rangekeep.llm._shared import table

    return judge(table(spark, sf_dir, "pages"))
