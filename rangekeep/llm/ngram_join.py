"""N-gram Jaccard join by parity sketches.

A text's set holds the distinct shingles of `k` words (A-Z lower-cased, ASCII blanks between); a shorter text's whole
sequence is its one shingle; a text without words has an empty set and links with nothing. Two texts link if
den * intersection >= num * union.

Bound: with Jaccard >= num/den, two sets of sizes m and n differ in at most (m + n)(den - num)/(den + num) shingles.
Each shingle toggles one bit of a sketch, so two sketches differ in no more bits than the sets in shingles. Sizes fall
into bands; in a band whose largest set has M shingles that bound is d(M), and the sketch is cut into more than d
blocks, so at least one block of two linked texts is equal. A block is a very wide row of bits that is never stored:
the exclusive or of a random word for each toggled bit stands for it. Only non-empty blocks say much, so a text sends
the d + 1 of them that come first in one global order (its non-empty blocks less those it may share is at most d);
the rare texts that have no more than d non-empty blocks send their empty ones too, which meet only each other.
A text whose partners may lie in the next band sends blocks of that band as well. Another, short sketch of 1024 bits
drops most chance meetings, and whole shingle sets verify the rest.

Groups: equal sets are folded first. In a bucket, every set is verified against the first and the last alone, then,
where that leaves several components, against one more drawn anew for each bucket. Only sets of one bucket that are
not connected after that are held against each other, so that no link between different components is lost and a
group of many near copies costs a multiple of its size. Where many are left, as in texts that share a passage and no
more, the bound is used once more: their short sketches are cut into more groups of bits than may differ, and only sets
that agree on one group meet.

Hot keys: a block that very many texts share is found from a share of the rows, folded where the rows lie and joined
back; all others meet in a window by key.

Nulls: a null text is empty; rows with a null id come back with a null component. An id
is taken to name one text; rows that share an id come back each with the component of its own set. An empty table gives an empty result. Extra columns are left out.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rangekeep.llm._graph import components
from rangekeep.llm._shared import chunks, forget, forget_since, keep, keep_parts, short_batches, small, trim, written

GROWTH = 1.5
SKETCH = 1024
PARTS = [f"k{i}" for i in range(SKETCH // 64)]
ROUNDS = 2
#: Rows of a key among one in HOT_SHARE from which it is folded first: about half a million in all.
HOT_SHARE, HOT = 128, 4096
#: Sent keys that meet at a time, and the most turns that this takes. They are the largest shuffle, and a window may spill as much again.
KEYS_AT_ONCE, TURNS = 4_000_000, 8
#: Sets of a bucket, not connected, beyond which their sketches divide them (a million pairs are compared in no time); and the most groups that a sketch is cut into.
MANY, GROUPS = 1000, 32
_C1, _C2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def _mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    x = x + np.uint64(salt)
    x = (x ^ (x >> np.uint64(30))) * _C1
    x = (x ^ (x >> np.uint64(27))) * _C2
    return x ^ (x >> np.uint64(31))


class _Words(dict):
    """Word -> 64-bit hash, remembered; starts anew when it is large."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 100_000:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


#: Bytes of a text that are cut into words at a time.
STRETCH = 1 << 18


def _hashes(text: bytes, known: _Words) -> np.ndarray:
    """Hashes of a text's words. bytes.lower() and split() know ASCII alone, as wanted; a long text goes stretch by stretch."""
    out, at = [], 0
    while at < len(text):
        end = at + STRETCH
        while end < len(text) and text[end] not in b" \t\n\x0b\f\r":
            end += 1
        found = text[at:end].lower().split()
        out.append(np.fromiter(map(known.__getitem__, found), np.uint64, len(found)))
        at = end
    return out[0] if len(out) == 1 else np.concatenate(out) if out else np.zeros(0, np.uint64)


def shingles(text: bytes | None, k: int, known: _Words) -> np.ndarray:
    """The sorted distinct 64-bit hashes of a text's shingles."""
    w = _hashes(text or b"", known)
    if not len(w):
        return w
    size = min(k, len(w))
    out = np.full(len(w) - size + 1, size, np.uint64)
    for j in range(size):
        out = _mix(out ^ w[j : len(w) - size + 1 + j], 0x9E37 + j)
    out.sort()
    return out[np.concatenate([[True], out[1:] != out[:-1]])]


def bands(largest: int, num: int, den: int) -> list[tuple[int, int]]:
    """Size bands [low, high), as far as `largest`; each is wide enough that partners lie in one band or the next."""
    growth, out, low = max(GROWTH, 1.01 * den / num), [], 1
    while low <= largest:
        high = max(low + 1, int(low * growth), -(-low * den // num) + 1)
        out.append((low, high))
        low = high
    return out


def most_apart(m: int, n: int, num: int, den: int) -> int:
    return (m + n) * (den - num) // (den + num)


def blocks(s: np.ndarray, num: int, den: int, edges: list[tuple[int, int]]) -> np.ndarray:
    """Keys of the blocks that a set sends, over its own band and, if partners may lie there, the next."""
    n, out = len(s), []
    for band, (low, high) in enumerate(edges):
        # the larger of two partners decides the band
        if not (low <= n < high or (n < low and n * den >= num * low)):
            continue
        d = most_apart(high - 1, high - 1, num, den)
        if d == 0:
            continue  # only equal sets link, and those are folded
        b = d + 1 + (d + 5) // 6 + 2
        block = (_mix(s, 0xB10C) % np.uint64(b)).astype(np.int64)
        parity = np.zeros(b, np.uint64)
        np.bitwise_xor.at(parity, block, _mix(s, 0x217))
        full = np.flatnonzero(np.bincount(block, minlength=b))
        keys = _mix(_mix(parity[full] ^ np.uint64(band << 40)) + full.astype(np.uint64), 0xF011)
        if len(full) > d:
            keys = np.partition(keys, d)[: d + 1]
        else:
            bare = np.setdiff1d(np.arange(b), full).astype(np.uint64)
            keys = np.concatenate([keys, _mix(bare + np.uint64(band << 40), 0xE3947)])
        out.append(keys)
    return np.concatenate(out) if out else np.zeros(0, np.uint64)


def fingerprint(s: np.ndarray) -> list[int]:
    """Two 64-bit hashes of the set and its short parity sketch in words of 64 bits."""
    h = _mix(s, 0x5E7)
    bits = np.bincount((h % np.uint64(SKETCH)).astype(np.int64), minlength=SKETCH) & 1
    sketch = np.packbits(bits.astype(np.uint8)).view(np.int64)
    both = [np.bitwise_xor.reduce(_mix(s, 0x11)), np.sum(_mix(s, 0x22), dtype=np.uint64)]
    return [int(np.uint64(x).astype(np.int64)) for x in both] + [int(x) for x in sketch]


def _marks(k: int, num: int, den: int):
    """Rows (id, text) -> id, set size, fingerprint and the keys of the blocks that the set sends."""

    def run(batches):
        known, edges, seen = _Words(), bands(64, num, den), set()
        none = np.zeros(0, np.uint64)
        for b in batches:
            named = b.column(0).is_valid().to_pylist()
            for lo, hi, texts in chunks(b.column(1)):
                rows, keys = [], []
                for t, ok in zip(texts, named[lo:hi], strict=True):
                    s = shingles(t, k, known)
                    mark = fingerprint(s) if len(s) else [0] * (2 + len(PARTS))
                    rows.append([len(s), *mark])
                    node = (mark[0], mark[1])
                    if not ok or not len(s) or node in seen:
                        keys.append(none)  # an equal set of this task has sent the same keys
                        continue
                    if len(seen) < 50_000:
                        seen.add(node)
                    if len(s) * den >= num * edges[-1][0]:
                        edges = bands(2 * len(s), num, den)
                    keys.append(blocks(s, num, den, edges))
                ends = np.concatenate([[0], np.cumsum([len(x) for x in keys])]).astype(np.int32)
                sent = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(keys).view(np.int64)))
                cols = np.array(rows, np.int64).T
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), *[pa.array(c) for c in cols], sent], ["id", "n", "s1", "s2", *PARTS, "keys"])
        known.clear()
        seen.clear()
        trim()

    return run


#: Bytes of shingle sets that a verifying task remembers.
HELD = 1 << 23


def _verified(k: int, num: int, den: int):
    def run(batches):
        known, held, size = _Words(), {}, [0]

        def of(key: int, text) -> np.ndarray:
            if key not in held:
                s = shingles(text.as_py(), k, known)
                if size[0] + s.nbytes > HELD:
                    held.clear()
                    size[0] = 0
                held[key], size[0] = s, size[0] + s.nbytes
            return held[key]

        for b in batches:
            ok = np.zeros(b.num_rows, bool)
            for i, (x, y) in enumerate(zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)):
                p, q = of(x, b.column(2)[i]), of(y, b.column(3)[i])
                both = len(np.intersect1d(p, q, assume_unique=True))
                ok[i] = both > 0 and den * both >= num * (len(p) + len(q) - both)
            yield pa.RecordBatch.from_arrays([c.filter(pa.array(ok)) for c in b.columns[:2]], ["a", "b"])
        known.clear()
        held.clear()
        trim()

    return run


def _near(x: str, y: str, num: int, den: int) -> Column:
    """Sizes and short sketches of two sets allow a link."""
    m, n = F.col(f"{x}n"), F.col(f"{y}n")
    apart = sum((F.bit_count(F.col(f"{x}k{i}").bitwiseXOR(F.col(f"{y}k{i}"))) for i in range(len(PARTS))), F.lit(0))
    return (den * F.least(m, n) >= num * F.greatest(m, n)) & (apart * (den + num) <= (m + n) * (den - num))


def _as(df: DataFrame, prefix: str) -> DataFrame:
    return df.select(*[F.col(c).alias(prefix + c) for c in df.columns])


def link(docs: DataFrame, text: str = "text", key: str = "doc_id", k: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """(key, n_shingles, component_id) for every row of docs; see the module for what links."""
    rows = docs.select(F.col(key).alias("id"), F.col(text).cast("binary").alias("t"))
    kind = docs.schema[key].dataType.simpleString()
    short_batches(docs.sparkSession)
    mark = written()
    longs = ", ".join(f"{c} long" for c in ("n", "s1", "s2", *PARTS))
    marks = keep(rows.mapInArrow(_marks(k, num, den), f"id {kind}, {longs}, keys array<long>"))
    real = marks.where(F.col("id").isNotNull() & (F.col("n") > 0))
    firsts = [F.first(c).alias(c) for c in ("n", *PARTS)]
    sets = keep(real.groupBy("s1", "s2").agg(F.min("id").alias("rep"), *firsts))

    met = keep_parts(_buckets(real.select(F.explode("keys").alias("key"), "s1"), _turns(real)))
    # the keys are most of the marks and have met
    ids = keep(marks.select("id", "n", "s1", "s2"))
    forget(marks)
    ends = met.select(F.explode(F.array(F.struct(F.col("lo").alias("x"), F.col("s1").alias("y")), F.struct(F.col("s1").alias("x"), F.col("hi").alias("y")))).alias("p"))
    stars = ends.select("p.x", "p.y").where("x < y").distinct()
    lean = sets.select("s1", "rep", "n", *PARTS)
    tested = stars.join(_as(lean, "a_"), F.col("x") == F.col("a_s1")).join(_as(lean, "b_"), F.col("y") == F.col("b_s1")).where(_near("a_", "b_", num, den))
    tested = keep(_ordered(tested))
    links = keep(verify(rows, tested, k, num, den))
    joined = components(links)

    # sets that one bucket holds and nothing connects: first each against one of its bucket, another in every bucket
    for turn in range(ROUNDS):
        open_ = _open(met, lean, joined)
        draw = F.struct(F.xxhash64(F.lit(turn), "key", "rep").alias("h"), *[c for c in open_.columns if c != "key"])
        centres = _as(open_.groupBy("key").agg(F.min(draw).alias("m")).select("key", "m.*").drop("h"), "a_")
        pairs = centres.join(_as(open_, "b_"), (F.col("a_key") == F.col("b_key")) & (F.col("a_c") != F.col("b_c")) & _near("a_", "b_", num, den))
        fresh = keep(_ordered(pairs).join(tested, ["a", "b"], "left_anti"))
        forget(open_)
        more = keep(verify(rows, fresh, k, num, den))
        tested = tested.unionByName(fresh)
        if not more.limit(1).count():
            break
        links = links.unionByName(more)
        forget(joined)
        joined = components(links)

    # then all that are left: what is linked in another way shares a component by now
    open_ = _open(met, lean, joined)
    crowded = keep(_crowded(open_, num, den))
    few = open_
    if crowded.limit(1).count():
        few = open_.join(small(crowded.select("key")), "key", "left_anti")
    cross = _as(few, "a_").join(_as(few, "b_"), (F.col("a_key") == F.col("b_key")) & (F.col("a_c") < F.col("b_c")) & _near("a_", "b_", num, den))
    fresh = _ordered(cross)
    if few is not open_:
        parted = _parted(open_, crowded)
        cross = _as(parted, "a_").join(_as(parted, "b_"), (F.col("a_part") == F.col("b_part")) & (F.col("a_c") < F.col("b_c")) & _near("a_", "b_", num, den))
        fresh = fresh.unionByName(_ordered(cross)).distinct()
    fresh = keep(fresh.join(tested, ["a", "b"], "left_anti"))
    late = keep(verify(rows, fresh, k, num, den))
    if late.limit(1).count():
        forget(joined)
        joined = components(links.unionByName(late))
    forget(met, open_)

    at = sets.join(joined, F.col("rep") == F.col("node"), "left").select("s1", "s2", F.coalesce("component", "rep").alias("component_id"))
    out = ids.join(at, ["s1", "s2"], "left")
    lone = F.when(F.col("id").isNotNull(), F.coalesce("component_id", "id"))
    out = keep(out.select(F.col("id").alias(key), F.col("n").alias("n_shingles"), lone.alias("component_id")))
    forget_since(mark, out)
    return out


def _turns(real: DataFrame) -> int:
    """In how many turns the sent keys meet."""
    n = real.agg(F.sum(F.size("keys").cast("bigint"))).first()[0] or 0
    return max(1, min(TURNS, -(-n // KEYS_AT_ONCE)))


def _buckets(sent: DataFrame, turns: int) -> Iterator[DataFrame]:
    """(key, s1, lo, hi): every block that two different sets sent, with the first and last of them; a part of all keys each turn.

    The keys go over the network once; a window spills, and a bucket has a row for each different set (and task that met it).
    """
    share = sent.where(F.pmod(F.xxhash64("s1", "key"), F.lit(HOT_SHARE)) == 0).groupBy("key").agg(F.count("*").alias("n"))
    hot = keep(share.where(F.col("n") >= HOT).select("key"))
    cold = sent
    if hot.limit(1).count():
        cold = sent.join(small(hot), "key", "left_anti")
    of_key = Window.partitionBy("key")
    for turn in range(turns):
        some = cold.where(F.pmod("key", F.lit(turns)) == turn)
        yield some.withColumns({"lo": F.min("s1").over(of_key), "hi": F.max("s1").over(of_key)}).where("lo < hi").distinct()
    if cold is sent:
        return
    warm = sent.join(small(hot), "key", "left_semi").distinct()
    ends = keep(warm.groupBy("key").agg(F.min("s1").alias("lo"), F.max("s1").alias("hi")).where("lo < hi"))
    yield warm.join(small(ends), "key").select("key", "s1", "lo", "hi")


def _crowded(open_: DataFrame, num: int, den: int) -> DataFrame:
    """(key, groups) of buckets of many open sets, with the groups into which their sketches are cut: sets of a bucket, none
    larger than M, differ in d(M) bits at most, so of d(M) + 1 groups one agrees."""
    sizes = open_.groupBy("key").agg(F.max("n").alias("big"), F.count("*").alias("m")).where(F.col("m") > MANY)
    groups = F.floor(2 * F.col("big") * (den - num) / (den + num)).cast("int") + 1
    return sizes.select("key", groups.alias("groups")).where((F.col("groups") > 1) & (F.col("groups") <= GROUPS))


def _parted(open_: DataFrame, crowded: DataFrame) -> DataFrame:
    """open_ of crowded buckets with a number `part` instead of the key: two sets of a bucket that may link share a part."""
    rows = open_.join(small(crowded), "key")
    halves = F.flatten(F.array(*[F.array(F.col(p).bitwiseAND(F.lit((1 << 32) - 1)), F.shiftrightunsigned(p, 32)) for p in PARTS]))
    of = lambda g: F.xxhash64("key", g, F.filter(F.col("halves"), lambda x, i: i % F.col("groups") == g))
    rows = rows.withColumn("halves", halves)
    return rows.withColumn("part", F.explode(F.transform(F.sequence(F.lit(0), F.col("groups") - 1), of))).drop("key", "groups", "halves")


def _ordered(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("a_rep", "b_rep").alias("a"), F.greatest("a_rep", "b_rep").alias("b")).where("a < b").distinct()


def _open(met: DataFrame, lean: DataFrame, joined: DataFrame) -> DataFrame:
    """(key, rep, n, sketch, c) of the buckets whose sets are not all in one component c."""
    names = lean.join(joined, F.col("rep") == F.col("node"), "left").select("s1", "rep", "n", *PARTS, F.coalesce("component", "rep").alias("c"))
    label = names.select("s1", "c")
    held = met.select("key", "s1").join(label, "s1")
    apart = held.groupBy("key").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo < hi").select("key")
    return keep(held.join(apart, "key", "left_semi").select("key", "s1").join(names, "s1").drop("s1"))


def verify(rows: DataFrame, pairs: DataFrame, k: int, num: int, den: int) -> DataFrame:
    """The pairs (a, b) of rows (id, t) that link, by their whole shingle sets."""
    needed = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()
    texts = rows.join(small(needed), "id", "left_semi")
    first = pairs.join(texts.select(F.col("id").alias("a"), F.col("t").alias("ta")), "a")
    both = first.join(texts.select(F.col("id").alias("b"), F.col("t").alias("tb")), "b")
    kind = pairs.schema["a"].dataType.simpleString()
    return both.select("a", "b", "ta", "tb").mapInArrow(_verified(k, num, den), f"a {kind}, b {kind}")


def query(spark, sf_dir: str) -> DataFrame:
    from rangekeep.llm._shared import table

    return link(table(spark, sf_dir, "documents"), k=4, num=85, den=100)
