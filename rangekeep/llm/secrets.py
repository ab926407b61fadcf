"""Secret scan: fixed patterns, and sliding-window entropy over long opaque strings, in DataFrame functions only.

Base kinds, leftmost and non-overlapping each: assign (a name such as password or token, a sign and a value of six or
more), access (AKIA and 16 or more capitals or digits), hex (24 or more of 0-9a-f). The method adds entropy spans:
candidates are runs of 20 or more of [A-Za-z0-9+/_=-]; a window of 20 slides over each and keeps the counts of its
characters and the sum of c log2 c over them; the character that leaves and the one that comes change both by a step. A candidate counts if its
largest window entropy reaches the limit of its class (hex digits or base64) and it touches no base span. Allow-listed
candidates (UUIDs, letters only, digits only, placeholders, running alphabets) are suppressed.

Positions are code points, ends exclusive. Null text counts as empty; repeated rows are scanned each alike; extra
columns are left out but for `columns`; an empty table gives an empty result. A text of any length is scanned whole.

Spark has no function for the places of matches: the gaps (split) and the matches (regexp_extract_all) of one pattern
alternate, so running sums of their lengths are the places. Running sums and extremes go by blocks of blocks, since an
array that grows by one element at a time costs the square of its length; all work is linear in the text but for one sort of its spans.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ASSIGN = "((?i:password|passwd|secret|token|api_?key))[\"']?\\x20*[:=]\\x20*[\"']?([A-Za-z0-9+/_.=-]+)"
ACCESS = "AKIA[A-Z0-9]{16,}"
HEX = "[0-9a-f]{24,}"
LONG = "[A-Za-z0-9+/_=-]{20,}"
KINDS = ("assign", "access", "hex", "entropy")
WINDOW = 20
HEX_BITS, BASE64_BITS = 3.0, 3.6
LEAST_VALUE = 6
#: Opaque-looking strings that are no secrets.
ALLOWED = (
    "^[0-9A-Fa-f]{8}-[0-9A-Fa-f]{4}-[0-9A-Fa-f]{4}-[0-9A-Fa-f]{4}-[0-9A-Fa-f]{12}$",
    "^[A-Za-z_/=+-]+$",
    "^[0-9_/=+-]+$",
    "(?i)example|sample|placeholder|dummy|changeme|your_|xxxx|0000|1234567|abcdefg",
)
SPAN = "array<struct<start:int,kind:int,end:int>>"


def _bind(value: Column, use) -> Column:
    return F.element_at(F.transform(F.array(value), use), 1)


#: Elements that a running sum appends one by one.
BLOCK = 64


def running(values: Column, start: Column, merge, kind: str, levels: int = 3) -> Column:
    """For each element of an array, `merge` over start and the elements before it."""

    def line(part: Column, first: Column) -> Column:
        zero = F.struct(first.cast(kind).alias("now"), F.array().cast(f"array<{kind}>").alias("out"))
        step = lambda a, v: F.struct(merge(a["now"], v).cast(kind).alias("now"), F.concat(a["out"], F.array(a["now"])).alias("out"))
        return F.aggregate(part, zero, step, lambda a: a["out"])

    def blocks(parts: Column) -> Column:
        folded = F.transform(parts, lambda p: F.aggregate(F.slice(p, 2, BLOCK), F.get(p, F.lit(0)), lambda a, v: merge(a, v).cast(kind)))
        return _bind(running(folded, start, merge, kind, levels - 1), lambda firsts: F.flatten(F.transform(parts, lambda p, i: line(p, F.get(firsts, i)))))

    def cut(v: Column) -> Column:
        starts = F.sequence(F.lit(1), F.greatest(F.size(v), F.lit(1)), F.lit(BLOCK))
        return F.when(F.size(v) <= BLOCK, line(v, start)).otherwise(_bind(F.transform(starts, lambda b: F.slice(v, b, BLOCK)), blocks))

    # a name for the array, which is else computed anew for every block
    return line(values, start) if levels == 1 else _bind(values, cut)


def places(text: Column, pattern: str) -> Column:
    """Structs (at, long, value) of the pattern's matches, leftmost and non-overlapping; value is the match."""
    none = F.array().cast("array<struct<at:int,long:int,value:string>>")

    def walk(hits: Column) -> Column:
        gaps = F.split(text, pattern, -1)

        def with_gaps(g: Column) -> Column:
            steps = F.transform(hits, lambda h, i: F.length(F.get(g, i)) + F.length(h))
            return _bind(running(steps, F.lit(0), lambda a, v: a + v, "int"), lambda before: F.transform(hits, lambda h, i: F.struct(
                (F.get(before, i) + F.length(F.get(g, i))).alias("at"), F.length(h).alias("long"), h.alias("value"))))

        return _bind(gaps, with_gaps)

    return F.when(text.rlike(pattern), _bind(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), walk)).otherwise(none)


def untouched(base: Column, found: Column) -> Column:
    """Of candidates (at, long, value), those that share no place with a base span (start, kind, end)."""
    far = (1 << 31) - 1
    spans = F.transform(base, lambda b: F.struct(b["start"].alias("at"), F.lit(0).alias("kind"), b["end"].alias("end"), F.lit(-1).alias("i")))
    mine = F.transform(found, lambda m, i: F.struct(m["at"].alias("at"), F.lit(1).alias("kind"), (m["at"] + m["long"]).alias("end"), i.alias("i")))

    def over(line: Column) -> Column:
        ends = F.transform(line, lambda x: F.when(x["kind"] == 0, x["end"]).otherwise(0))
        starts = F.transform(F.reverse(line), lambda x: F.when(x["kind"] == 0, x["at"]).otherwise(far))
        reach = running(ends, F.lit(0), F.greatest, "int")  # the last end of a span that starts before
        ahead = running(starts, F.lit(far), F.least, "int")  # the first start of one that comes after
        return _bind(reach, lambda r: _bind(ahead, lambda a: F.filter(F.transform(line, lambda x, i: F.when(
            (x["kind"] == 1) & (F.get(r, i) <= x["at"]) & (F.get(a, F.size(line) - 1 - i) >= x["end"]), x["i"])), lambda i: i.isNotNull())))

    free = _bind(F.array_sort(F.concat(spans, mine)), over)
    return F.when(F.size(base) == 0, found).otherwise(_bind(free, lambda held: F.transform(held, lambda i: F.get(found, i))))


def _f(c: Column) -> Column:
    return F.when(c > 1, c * F.log2(c.cast("double"))).otherwise(0.0)


#: Characters of a candidate; each has a count of its own in the window.
LETTERS = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"


def most_entropy(value: Column, window: int = WINDOW) -> Column:
    """Largest Shannon entropy, in bits a character, of a window sliding over value. Characters beyond LETTERS count as one."""
    # the chars' numbers as an array, so that a step costs the same however long the string is
    numbers = F.transform(F.regexp_extract_all(value, F.lit("."), F.lit(0)), lambda x: F.instr(F.lit(LETTERS), x))

    def over(c: Column) -> Column:
        first = F.slice(c, 1, window)
        counts = F.transform(F.sequence(F.lit(0), F.lit(len(LETTERS))), lambda k: F.size(F.filter(first, lambda y: y == k)))
        start = F.aggregate(counts, F.lit(0.0), lambda s, n: s + _f(n))

        def step(a: Column, i: Column) -> Column:
            out, come = F.get(c, i - window), F.get(c, i)
            n_out, n_come = F.get(a["n"], out), F.get(a["n"], come)
            s = F.when(out == come, a["s"]).otherwise(a["s"] - _f(n_out) + _f(n_out - 1) + _f(n_come + 1) - _f(n_come))
            n = F.when(out == come, a["n"]).otherwise(F.transform(a["n"], lambda v, k: v + (k == come).cast("int") - (k == out).cast("int")))
            return F.struct(n.alias("n"), s.alias("s"), F.least(a["least"], s).alias("least"))

        rest = F.when(F.size(c) > window, F.sequence(F.lit(window), F.size(c) - 1)).otherwise(F.array().cast("array<int>"))
        zero = _bind(counts, lambda n: F.struct(n.alias("n"), start.alias("s"), start.alias("least")))
        least = F.aggregate(rest, zero, step, lambda a: a["least"])
        return F.log2(F.least(F.size(c), F.lit(window)).cast("double")) - least / F.least(F.size(c), F.lit(window))

    return _bind(numbers, over)


def scan(docs: DataFrame, text: str = "text", columns: tuple[str, ...] = ("doc_id",), allowed: tuple[str, ...] = ALLOWED, window: int = WINDOW, hex_bits: float = HEX_BITS, base64_bits: float = BASE64_BITS) -> DataFrame:
    """columns, and found: the spans (start, kind, end) by start and kind; kinds are numbered as in KINDS."""
    t = F.coalesce(F.col(text), F.lit(""))

    def span(c: Column, kind: int) -> Column:
        return F.transform(c, lambda m: F.struct(m["at"].alias("start"), F.lit(kind).alias("kind"), (m["at"] + m["long"]).alias("end"))).cast(SPAN)

    rows = docs.select(*columns, t.alias("__t"))
    values = F.regexp_extract_all(F.col("__t"), F.lit(ASSIGN), F.lit(2))
    assign = _bind(places(F.col("__t"), ASSIGN), lambda p: F.when(F.size(p) == 0, p).otherwise(
        _bind(values, lambda v: F.filter(p, lambda m, i: F.length(F.get(v, i)) >= LEAST_VALUE))))
    base = F.array_sort(F.concat(span(assign, 0), span(places(F.col("__t"), ACCESS), 1), span(places(F.col("__t"), HEX), 2)))
    rows = rows.select(*columns, base.alias("__base"), places(F.col("__t"), LONG).alias("__long"))

    def secret(m: Column) -> Column:
        calm = m["value"].rlike(allowed[0])
        for a in allowed[1:]:
            calm = calm | m["value"].rlike(a)
        limit = F.when(m["value"].rlike("^[0-9A-Fa-f]+$"), hex_bits).otherwise(base64_bits)
        return ~calm & (most_entropy(m["value"], window) >= limit)

    free = _bind(untouched(F.col("__base"), F.col("__long")), lambda m: span(F.filter(m, secret), 3))
    more = F.when(F.size("__long") == 0, F.array().cast(SPAN)).otherwise(free)
    return rows.select(*columns, F.array_sort(F.concat("__base", more)).alias("found"))


def digest(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"], s["end"])), ",")


def count(spans: Column, kind: str) -> Column:
    # of one argument only: a second one would be the place in the array
    return F.size(F.filter(spans, lambda s: s["kind"] == KINDS.index(kind))).cast("long")


def query(spark, sf_dir: str) -> DataFrame:
    from rangekeep.llm._shared import table

    out = scan(table(spark, sf_dir, "documents"))
    numbers = [count(F.col("found"), k).alias(f"n_{k}") for k in KINDS[:3]]
    return out.select("doc_id", *numbers, F.sha2(digest(F.filter("found", lambda s: s["kind"] < 3)), 256).alias("base_sha256"), digest(F.col("found")).alias("spans"))
