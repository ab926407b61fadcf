"""Quality rules by distribution divergence, in DataFrame functions only.

Base counts of each text (null: empty): n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words. A document fails
the base if it has under 50 words or if repeated three-word windows cover over half of its words.

The method compares two histograms of each document with those of its language over the whole corpus, by
Jensen-Shannon distance (the root of the divergence in bits): classes of characters (lower, upper, digit, space, mark,
other) and the share of each of some very frequent words. A language's reference is its documents' counts and, as a
prior, the corpus's shares for `prior` characters or words, so that a language of few documents leans on the corpus a
little and one of many not at all, without a step between them. A document without a language is held against every
language, and the nearest counts; all are also held against the corpus, since a text in several languages is near it.
A text of under `least_words` words isn't judged by the method, and the limit for common words is wider by `noise` /
n_words under the root, since short texts stray. Where no document has a language the base rules alone decide.
Languages are a few hundred at most, so their references are sent to the rows.

Extra columns stay out of the result but `columns`; repeated rows are judged each alike; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rangekeep.llm._shared import keep, small

# Very frequent function words of four languages.
COMMON = ("the", "of", "and", "to", "in", "is", "der", "die", "und", "das", "ein", "von", "de", "la", "le", "et", "les", "que", "el", "en", "y", "los", "a", "un")
LEAST_WORDS = 50
#: Squares of the largest distances; the second grows by COMMON_NOISE / n_words.
MOST_CLASSES = 0.05
MOST_COMMON, COMMON_NOISE = 0.058, 0.8
#: Characters or words of the corpus in a language's reference.
PRIOR = 1000.0


def _less(text: Column, chars: str) -> Column:
    """How many characters of text are among chars."""
    return F.length(text) - F.length(F.translate(text, chars, ""))


def _bind(value: Column, use) -> Column:
    """use(value) with value computed once: a one-element array gives it a name."""
    return F.element_at(F.transform(F.array(value), use), 1)


def split_words(text: Column) -> Column:
    return F.filter(F.split(text, "[\\x20\\x09-\\x0D]+", -1), lambda w: w != "")


def common_words(ws: Column, n: Column) -> Column:
    """Counts of each common word, as it stands, and of all the other words."""
    held = F.filter(ws, lambda w: w.isin(*COMMON))

    def count(bare: Column) -> Column:
        joined = F.concat(F.lit(" "), F.array_join(bare, "  "), F.lit(" "))
        each = [((F.length(joined) - F.length(F.replace(joined, F.lit(f" {w} "), F.lit("")))) / (len(w) + 2)).cast("long") for w in COMMON]
        return F.array(*each, (n - F.size(bare)).cast("long"))

    return _bind(held, count)


def repeated(ws: Column) -> Column:
    """How many words lie in a three-word window that the text has twice or more."""
    places = F.sequence(F.lit(0), F.size(ws) - 3)
    windows = F.transform(places, lambda i: F.xxhash64(F.get(ws, i), F.get(ws, i + 1), F.get(ws, i + 2)))
    some = F.when(F.size(ws) < 4, F.array().cast("array<bigint>")).otherwise(windows)
    return _bind(some, lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(_covered(h)))


FEW = 24


def _covered(h: Column) -> Column:
    """Words under windows whose hash comes again. Few such hashes are looked up one by one, many are found by sorting."""
    at = F.sequence(F.lit(0), F.size(h) - 1)

    def sorted_places() -> Column:
        spots = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
        return _bind(spots, lambda s: F.array_sort(F.filter(F.transform(s, lambda x, k: F.when(
            ((k > 0) & (x["h"] == F.get(s, k - 1)["h"])) | (x["h"] == F.get(s, k + 1)["h"]), x["i"])), lambda p: p.isNotNull())))

    def looked_up(again: Column) -> Column:
        return F.when(F.size(again) <= FEW, F.filter(at, lambda i: F.array_contains(again, F.get(h, i)))).otherwise(sorted_places())

    def count(p: Column) -> Column:
        step = lambda a, i: F.struct((a["n"] + F.least(F.lit(3), i - a["at"])).alias("n"), i.alias("at"))
        return F.aggregate(p, F.struct(F.lit(0).alias("n"), F.lit(-9).alias("at")), step, lambda a: a["n"])

    again = _bind(F.sort_array(h), lambda s: F.array_distinct(F.filter(s, lambda x, k: x == F.get(s, k - 1))))
    return count(_bind(again, looked_up))


def duplicate_lines(text: Column) -> Column:
    ls = F.filter(F.split(text, "\n", -1), lambda x: x.rlike("[^\\x20\\x09-\\x0D]"))
    return _bind(ls, lambda a: F.size(a) - F.size(F.array_distinct(a)))


def measures(docs: DataFrame, text: str = "text", lang: str = "lang", columns: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Base counts, the counts of characters by class (lower, upper, digit, blank, mark, other) and of common words."""
    rows = docs.select(*columns, F.col(lang).alias("__lang"), F.coalesce(F.col(text), F.lit("")).alias("__t"))
    # each step takes one class out of what the step before has left, which is short after the first
    rows = rows.withColumn("__1", F.regexp_replace("__t", "\\p{Ll}+", ""))
    rows = rows.withColumn("__2", F.regexp_replace("__1", "\\p{Lu}+", ""))
    rows = rows.withColumn("__3", F.regexp_replace("__2", "[0-9]+", ""))
    rows = rows.withColumn("__4", F.regexp_replace("__3", "[\\x20\\x09-\\x0D]+", ""))
    rows = rows.withColumn("__5", F.regexp_replace("__4", "[!-/:-@\\[-`{-~]+", ""))
    long = [F.length(c) for c in ("__t", "__1", "__2", "__3", "__4", "__5")]
    split = [(x - y).cast("long") for x, y in zip(long, long[1:], strict=False)] + [long[-1].cast("long")]
    rows = rows.select(
        *columns, "__lang", (long[0] - long[3] + long[4]).cast("long").alias("word_chars"), _less(F.col("__4"), "#*$%&|<>").cast("long").alias("n_symbols"),
        duplicate_lines(F.col("__t")).cast("long").alias("n_dup_lines"), F.array(*split).alias("__classes"), split_words(F.col("__t")).alias("__w"),
    )
    n = F.size("__w").cast("long")
    return rows.select(
        *columns, "__lang", n.alias("n_words"), "word_chars", "n_symbols", "n_dup_lines", repeated(F.col("__w")).cast("long").alias("n_repeat_words"),
        "__classes", common_words(F.col("__w"), n).alias("__common"),
    )


def references(measured: DataFrame, prior: float = PRIOR) -> DataFrame:
    """(__of, __r_classes, __r_common): each language's histograms with the prior, and the whole corpus's (language null)."""
    parts = [(c, i) for c, n in (("__classes", 6), ("__common", len(COMMON) + 1)) for i in range(n)]
    folded = measured.rollup("__lang").agg(F.grouping("__lang").alias("all"), *[F.sum(F.col(c)[i]).cast("double").alias(f"{c}{i}") for c, i in parts])
    # the corpus's own sums are the largest of each column, and stand beside each language's
    whole = folded.where("all = 1").select(*[F.col(f"{c}{i}").alias(f"w{c}{i}") for c, i in parts])
    rows = folded.where((F.col("all") == 1) | F.col("__lang").isNotNull()).join(F.broadcast(whole), F.lit(True))

    def smooth(c: str, n: int) -> Column:
        total = sum((F.coalesce(F.col(f"w{c}{i}"), F.lit(0.0)) for i in range(n)), F.lit(0.0))
        return F.array(*[F.col(f"{c}{i}") + F.when(total > 0, prior * F.col(f"w{c}{i}") / total).otherwise(0.0) for i in range(n)])

    return rows.select(F.when(F.col("all") == 0, F.col("__lang")).alias("__of"), smooth("__classes", 6).alias("__r_classes"), smooth("__common", len(COMMON) + 1).alias("__r_common"))


def divergence(a: Column, b: Column) -> Column:
    """Jensen-Shannon divergence, in bits, of two arrays of counts of one length; 1 if either is empty."""
    na, nb = (F.aggregate(x, F.lit(0.0), lambda s, v: s + v) for x in (a, b))
    shares = F.zip_with(a, b, lambda x, y: F.struct((x / na).alias("p"), (y / nb).alias("q")))

    def part(p: Column, q: Column) -> Column:
        return F.when(p > 0, p * F.log2(2 * p / (p + q))).otherwise(0.0)

    total = F.aggregate(shares, F.lit(0.0), lambda s, x: s + part(x["p"], x["q"]) + part(x["q"], x["p"]))
    return F.when((na > 0) & (nb > 0), total / 2).otherwise(1.0)


def judge(measured: DataFrame, least_words: int = LEAST_WORDS, most_classes: float = MOST_CLASSES, most_common: float = MOST_COMMON, noise: float = COMMON_NOISE, prior: float = PRIOR) -> DataFrame:
    """measured with base_failed, the two distances and kept."""
    refs = keep(references(measured, prior))
    # the sums over the whole corpus are one row of some thirty numbers
    whole = {"classes": [], "common": []} | {k: r[f"__r_{k}"] for r in refs.where(F.col("__of").isNull()).collect() for k in ("classes", "common")}
    whole = {k: F.array(*[F.lit(x) for x in v]).cast("array<double>") for k, v in whole.items()}
    own = refs.where(F.col("__of").isNotNull())
    # a language may hold a third of all rows: the few references go to the rows, not the rows to them
    rows = measured.join(small(own), F.col("__lang") == F.col("__of"), "left")
    # one row of all languages' references, for the rows that have none of their own
    every = own.agg(F.collect_list(F.struct(F.col("__r_classes").alias("classes"), F.col("__r_common").alias("common"))).alias("__every"))
    rows = rows.join(F.broadcast(every), F.col("__of").isNull(), "left")

    def near(c: str) -> Column:
        counts = F.col(f"__{c}").cast("array<double>")
        nearest = F.array_min(F.transform("__every", lambda r: divergence(counts, r[c])))
        mine = F.when(F.col("__of").isNotNull(), divergence(counts, F.col(f"__r_{c}"))).otherwise(nearest)
        # rounding may leave a divergence of none just under zero
        return F.sqrt(F.greatest(F.lit(0.0), F.least(mine, divergence(counts, whole[c]))))

    rows = rows.withColumns({
        "jsd_classes": near("classes"),
        "jsd_common": near("common"),
        "base_failed": (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words")),
    })
    held = F.col("__of").isNotNull() | (F.size("__every") > 0)
    odd = held & (F.col("n_words") >= least_words) & ((F.col("jsd_classes") > F.lit(most_classes**0.5)) | (F.col("jsd_common") > F.sqrt(most_common + noise / F.col("n_words"))))
    return rows.withColumn("kept", ~F.col("base_failed") & ~odd).drop("__lang", "__classes", "__common", "__of", "__r_classes", "__r_common", "__every")


def apply(docs: DataFrame, text: str = "text", lang: str = "lang", columns: tuple[str, ...] = ("doc_id",), **how) -> DataFrame:
    return judge(keep(measures(docs, text, lang, columns)), **how)


def query(spark, sf_dir: str) -> DataFrame:
    from rangekeep.llm._shared import table

    return apply(table(spark, sf_dir, "documents"))
