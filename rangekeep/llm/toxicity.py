"""Toxicity: FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Words are runs of letters and digits, lower-cased. A text's features are the distinct hashes of its words, of their
first four and five characters (a light stem, since abuse is inflected), of its word pairs and of its pairs with one
word skipped. fit() learns from a bounded sample of labelled rows; L1 leaves few weights, which are broadcast.

Null text counts as empty and gets the bias alone. Rows repeat as often as they came; extra columns stay unless they
carry a result's name, in which case the result replaces them. An empty table gives an empty result; with no labels
of both kinds every score is the share of label 1 (0 if there are none).
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangekeep.llm._shared import chunks, pieces, short_batches, trim

WORD = re.compile(r"\w+")
BITS = 20
MOST_TRAIN = 12_000
THRESHOLD = 0.3


class Vocabulary(dict):
    """Word -> row in a table of hashes (word, four-letter stem, five-letter stem); forgets all when it is full."""

    def __init__(self, most: int = 100_000):
        self.most, self.fresh, self.table = most, [], np.zeros((0, 3), np.uint64)

    def __missing__(self, word: str) -> int:
        h = xxhash.xxh3_64_intdigest
        self.fresh.append((h(word), h("4" + word[:4]), h("5" + word[:5])))
        self[word] = n = len(self.table) + len(self.fresh) - 1
        return n

    def ids(self, found: list[str]) -> tuple[np.ndarray, np.ndarray]:
        if len(self) > self.most:
            self.clear()
            self.table = self.table[:0]
        ids = np.fromiter(map(self.__getitem__, found), np.int64, len(found))
        if self.fresh:
            self.table = np.concatenate([self.table, np.array(self.fresh, np.uint64)])
            self.fresh = []
        return ids, self.table


def features(texts: list[bytes | None], vocabulary: Vocabulary, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """(text number, feature number) of all grams of all texts, with repeats."""
    found: list[str] = []
    ends = np.zeros(len(texts), np.int64)
    for i, t in enumerate(texts):
        if t:
            found += WORD.findall(t.decode("utf-8", "replace").lower())
        ends[i] = len(found)
    if not found:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    ids, table = vocabulary.ids(found)
    doc = np.repeat(np.arange(len(texts)), np.diff(ends, prepend=0))
    hashes = table[ids]
    w = hashes[:, 0]
    parts, owners = [hashes[:, 0], hashes[:, 1], hashes[:, 2]], [doc, doc, doc]
    for gap, salt in ((1, 0x9E3779B97F4A7C15), (2, 0xC2B2AE3D27D4EB4F)):
        same = doc[gap:] == doc[:-gap]
        pair = (w[:-gap] * np.uint64(salt)) ^ (w[gap:] + np.uint64(salt >> 7))
        pair = (pair ^ (pair >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
        parts.append(pair[same])
        owners.append(doc[gap:][same])
    grams = np.concatenate(parts) >> np.uint64(64 - bits)
    return np.concatenate(owners), grams.astype(np.int64)


@dataclass
class Model:
    """Sparse weights: feature numbers, their weights and the bias."""

    at: np.ndarray
    weight: np.ndarray
    bias: float
    bits: int = BITS

    def dense(self) -> np.ndarray:
        out = np.zeros(1 << self.bits)
        out[self.at] = self.weight
        return out


def _distinct(x: np.ndarray) -> np.ndarray:
    x = np.sort(x)
    return x[np.concatenate([[True], x[1:] != x[:-1]])] if len(x) else x


def _logistic(x):
    return 1 / (1 + np.exp(-np.clip(x, -35, 35)))


def learn(rows: list[np.ndarray], labels: np.ndarray, bits: int = BITS, alpha=0.3, beta=1.0, l1=2.0, l2=0.5, epochs=6, least_df=3) -> Model:
    """FTRL-proximal over rows of distinct feature numbers, in the order given; features in fewer rows are left out."""
    share = float(labels.mean()) if len(labels) else 0.0
    if not len(labels) or share in (0.0, 1.0):
        return Model(np.zeros(0, np.int64), np.zeros(0), float(np.log((share + 1e-9) / (1 - share + 1e-9))), bits)
    df = np.zeros(1 << bits, np.int32)
    for r in rows:
        df[r] += 1  # a row's features are distinct
    for i, r in enumerate(rows):
        rows[i] = r[df[r] >= least_df]
    z, n, w = np.zeros(1 << bits), np.zeros(1 << bits), np.zeros(1 << bits)
    bias, bias_n = float(np.log(share / (1 - share))), 0.0
    for _ in range(epochs):
        for r, y in zip(rows, labels, strict=True):
            g = float(_logistic(bias + w[r].sum())) - y
            bias_n += g * g
            bias -= 0.05 * g / (1 + bias_n**0.5)
            old = n[r]
            new = old + g * g
            z[r] += g - (np.sqrt(new) - np.sqrt(old)) / alpha * w[r]
            n[r] = new
            zr = z[r]
            w[r] = np.where(np.abs(zr) <= l1, 0.0, -(zr - np.sign(zr) * l1) / ((beta + np.sqrt(new)) / alpha + l2))
    at = np.flatnonzero(w)
    return Model(at, w[at], bias, bits)


def _distinct_features(bits: int):
    def run(batches):
        vocabulary = Vocabulary()
        for b in batches:
            for lo, hi, texts in chunks(b.column(1), 1_000_000):
                doc, gram = features(texts, vocabulary, bits)
                both = _distinct((doc << bits) | gram)
                doc, gram = both >> bits, (both & ((1 << bits) - 1)).astype(np.int32)
                ends = np.searchsorted(doc, np.arange(hi - lo + 1)).astype(np.int32)
                cut = pa.ListArray.from_arrays(ends, pa.array(gram))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), b.column(2).slice(lo, hi - lo), cut], ["k", "label", "gram"])
        vocabulary.clear()
        trim()

    return run


def sample(labels: DataFrame, key: str = "doc_id", most: int = MOST_TRAIN) -> DataFrame:
    """At most `most` rows of labels, those first by a hash of their key; the same for the same rows."""
    return labels.withColumn("__k", F.xxhash64(F.lit("toxicity"), F.col(key))).orderBy("__k", *labels.columns).limit(most).drop("__k")


def fit(labelled: DataFrame, text: str = "text", label: str = "label", key: str = "doc_id", most: int = MOST_TRAIN, bits: int = BITS, **how) -> Model:
    """A model from labelled rows, in the order of a hash of their key; null labels are left out.

    One task learns, so labelled comes from sample(), which bounds it; beyond `most` rows none counts. Only the sparse
    weights reach the driver.
    """
    rows = labelled.where(F.col(label).isNotNull()).select(
        F.xxhash64(F.lit("toxicity"), F.col(key)).alias("k"), F.coalesce(F.col(text), F.lit("")).cast("binary").alias("t"), F.col(label).cast("int").alias("label")
    )
    short_batches(rows.sparkSession)
    grams = rows.mapInArrow(_distinct_features(bits), "k long, label int, gram array<int>")
    one = grams.repartition(1).sortWithinPartitions("k", "label").mapInArrow(_learner(most, bits, how), "at array<int>, weight array<double>, bias double")
    got = one.first()
    if got is None:
        return learn([], np.zeros(0), bits)
    return Model(np.array(got["at"], np.int64), np.array(got["weight"]), got["bias"], bits)


def _learner(most: int, bits: int, how: dict):
    """One task learns from the bounded sample, away from the driver's memory; a lost executor means that it is done again."""

    def run(batches):
        rows, y = [], []
        for b in batches:
            lists = b.column(2)
            ends, flat = np.asarray(lists.offsets), np.asarray(lists.values)
            rows += [flat[ends[i] : ends[i + 1]] for i in range(b.num_rows)][: most - len(rows)]
            y += b.column(1).to_pylist()
        m = learn(rows, np.array(y[: len(rows)], float).clip(0, 1), bits, **how)
        yield pa.RecordBatch.from_arrays([pa.array([m.at.astype(np.int32)], pa.list_(pa.int32())), pa.array([m.weight], pa.list_(pa.float64())), pa.array([m.bias])], ["at", "weight", "bias"])
        rows.clear()
        trim()

    return run


def score_texts(texts: list[bytes | None], model: Model, weights: np.ndarray, vocabulary: Vocabulary) -> np.ndarray:
    out = np.zeros(len(texts))
    for lo, hi in pieces(texts, 1_000_000):
        doc, gram = features(texts[lo:hi], vocabulary, model.bits)
        hit = weights[gram] != 0
        both = _distinct((doc[hit] << model.bits) | gram[hit])
        out[lo:hi] = np.bincount(both >> model.bits, weights[both & ((1 << model.bits) - 1)], hi - lo)
    return _logistic(out + model.bias)


def _scores(model: Model, n: int):
    def run(batches):
        vocabulary, weights = Vocabulary(), model.dense()
        for b in batches:
            p = np.concatenate([np.zeros(0), *[score_texts(texts, model, weights, vocabulary) for _, _, texts in chunks(b.column(n))]])
            yield pa.RecordBatch.from_arrays([*b.columns[:n], pa.array(p)], [*b.schema.names[:n], "score"])
        vocabulary.clear()
        del weights
        trim()

    return run


def score(docs: DataFrame, model: Model, text: str = "text", columns: list[str] | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """columns of docs (all by default) with score and predicted."""
    kept = [docs[c] for c in (columns or docs.columns) if c not in ("score", "predicted")]
    rows = docs.select(*kept, F.col(text).cast("binary").alias("__text"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[:-1])
    short_batches(docs.sparkSession)
    out = rows.mapInArrow(_scores(model, len(kept)), f"{schema}{', ' if schema else ''}score double")
    return out.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def query(spark, sf_dir: str) -> DataFrame:
    from rangekeep.llm._shared import table

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    held = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(4)) == 2
    labels = table(spark, sf_dir, "labels").select("doc_id", F.col("toxic").alias("label"))
    model = fit(docs.join(F.broadcast(sample(labels.where(~held & F.col("label").isNotNull()))), "doc_id"))
    out = score(docs, model, columns=["doc_id"])
    return out.select("doc_id", F.coalesce(held, F.lit(False)).alias("held_out"), "score", "predicted")
