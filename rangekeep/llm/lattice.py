"""Embedding near-dedup by lattice hashing: E8 cells of random projections, verified by cosine.

Each of `tables` tables projects a vector of length one to eight coordinates by random normals, scales them and takes
the nearest point of the lattice E8 as its cell; it also visits the `probes` cells next to it that lie nearest. Two
vectors meet where one's own cell is a cell that the other has or visits, and link if their cosine, in double
precision, is at least `least`. Of all their meeting places, the pair counts in the smallest alone.

Equal vectors (component by component) are folded first and count through their number. Null or zero vectors and
those with null or non-finite components link with nothing. Vectors of other lengths meet only their own kind. A cell
with many vectors is cut into blocks of `BLOCK`, and each pair of blocks is one task's work in one matrix product, so
no pair is ever a row and no group is gathered whole. Null ids, repeated rows: each row is returned; rows sharing an
id count each as a vector. An empty table gives an empty result. Extra columns are left out.

Shape: (cell, vector) rows of sixteen bytes find the cells where two vectors meet; only those carry vectors.
"""

from __future__ import annotations

from itertools import combinations, product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangekeep.llm._graph import components
from rangekeep.llm._shared import forget, keep

TABLES, PROBES, SCALE, LEAST, BLOCK = 20, 12, 1.3, 0.9, 1500
SHORT = 24


def roots() -> np.ndarray:
    """The 240 shortest vectors of E8: two coordinates of one, or all of a half with an even number of minus signs."""
    pairs = []
    for i, j in combinations(range(8), 2):
        for a, b in product((1.0, -1.0), repeat=2):
            v = np.zeros(8)
            v[i], v[j] = a, b
            pairs.append(v)
    halves = [np.array(s) / 2 for s in product((1.0, -1.0), repeat=8) if np.prod(s) > 0]
    return np.array(pairs + halves)


def _even(x: np.ndarray) -> np.ndarray:
    """Nearest integer point with an even sum: if rounding gives an odd one, the worst rounded coordinate goes the other way."""
    r = np.rint(x)
    off = x - r
    worst = np.abs(off).argmax(1)
    i = np.arange(len(x))
    step = np.where(off[i, worst] >= 0, 1.0, -1.0)
    odd = (r.sum(1) % 2) != 0
    r[i[odd], worst[odd]] += step[odd]
    return r


def decode(x: np.ndarray) -> np.ndarray:
    """Nearest E8 point of each row: the better of the even integer points and those shifted by a half."""
    a, b = _even(x), _even(x - 0.5) + 0.5
    closer = ((x - a) ** 2).sum(1) <= ((x - b) ** 2).sum(1)
    return np.where(closer[:, None], a, b)


def planes(dim: int, tables: int, seed: int = 8) -> np.ndarray:
    return np.random.default_rng([seed, dim]).standard_normal((dim, tables * 8))


_ODD = np.random.default_rng(88).integers(1, 1 << 63, 9, np.uint64) * np.uint64(2) + np.uint64(1)


def _name(points: np.ndarray, t: int, dim: int) -> np.ndarray:
    """64-bit name of each lattice point of table t."""
    n = np.rint(points * 2).astype(np.int64).astype(np.uint64)
    h = (n * _ODD[:8]).sum(-1, dtype=np.uint64) + np.uint64((t + 1 + 1000 * dim) * int(_ODD[8]) % (1 << 64))
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return (h ^ (h >> np.uint64(29))).view(np.int64)


def cells(x: np.ndarray, tables: int = TABLES, probes: int = PROBES, scale: float = SCALE) -> tuple[np.ndarray, np.ndarray]:
    """(own cells: rows by tables, visited cells: rows by tables by probes) of unit vectors."""
    near, dim = roots(), x.shape[1]
    y = x @ planes(dim, tables) * scale
    own, visits = np.empty((len(x), tables), np.int64), np.empty((len(x), tables, probes), np.int64)
    for t in range(tables):
        at = y[:, 8 * t : 8 * t + 8]
        c = decode(at)
        own[:, t] = _name(c, t, dim)
        if probes:
            best = np.argpartition(-((at - c) @ near.T), probes - 1, axis=1)[:, :probes]
            visits[:, t] = _name(c[:, None, :] + near[best], t, dim)
    return own, visits


def _matrix(column: pa.Array) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each length of the vectors in a list column: their row numbers and them, in double precision, of length one."""
    ends = np.asarray(column.offsets)
    long, flat = np.diff(ends), np.asarray(column.values, np.float64)
    out = []
    for d in np.unique(long):
        at = np.flatnonzero(long == d)
        x = flat[(ends[at][:, None] + np.arange(d)).ravel()].reshape(len(at), d)
        out.append((at, x / np.sqrt((x * x).sum(1))[:, None]))
    return out


def _emit(tables: int, probes: int, scale: float):
    def run(batches):
        for b in batches:
            ids = np.asarray(b.column(0))
            for at, x in _matrix(b.column(1)):
                for lo in range(0, len(at), 2000):
                    own, visits = cells(x[lo : lo + 2000], tables, probes, scale)
                    part = ids[at[lo : lo + 2000]]
                    cell = np.concatenate([own.ravel(), visits.ravel()])
                    who = np.concatenate([np.repeat(part, tables), np.repeat(part, tables * probes)])
                    mine = np.zeros(len(cell), bool)
                    mine[: own.size] = True
                    yield pa.RecordBatch.from_arrays([pa.array(cell), pa.array(who), pa.array(mine)], ["cell", "rep", "own"])

    return run


def _near_pairs(x: np.ndarray, group: np.ndarray, own: np.ndarray, part: np.ndarray, cross: np.ndarray, least: float):
    """Index pairs of rows of one group that may meet and whose cosine is at least `least`; groups stand together."""
    starts = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
    sizes = np.diff(np.append(starts, len(group)))
    size_of = np.repeat(sizes, sizes)
    left, right = [], []

    def take(i, j):
        ok = (own[i] | own[j]) & (~cross[i] | (part[i] != part[j]))
        left.append(i[ok])
        right.append(j[ok])

    # short groups: all rows against the k-th after them, where that is of the same group
    for k in range(1, min(SHORT, int(sizes.max(initial=0)))):
        i = np.flatnonzero((group[:-k] == group[k:]) & (size_of[:-k] <= SHORT))
        good = np.einsum("ij,ij->i", x[i], x[i + k]) >= least
        take(i[good], i[good] + k)
    for s, n in zip(starts[sizes > SHORT], sizes[sizes > SHORT], strict=True):
        m = x[s : s + n]
        for lo in range(0, n, 512):
            i, j = np.nonzero(m[lo : lo + 512] @ m.T >= least)
            up = i + lo < j
            take(i[up] + lo + s, j[up] + s)
    return (np.concatenate(left), np.concatenate(right)) if left else (np.zeros(0, np.int64), np.zeros(0, np.int64))


def _labels(i: np.ndarray, j: np.ndarray, n: int) -> np.ndarray:
    """Smallest number reachable over the pairs, for each of n numbers."""
    lab = np.arange(n)
    while True:
        low = np.minimum(lab[i], lab[j])
        new = lab.copy()
        np.minimum.at(new, i, low)
        np.minimum.at(new, j, low)
        np.minimum.at(new, lab[i], low)
        np.minimum.at(new, lab[j], low)
        new = new[new]
        if (new == lab).all():
            return lab
        lab = new


def _links(tables: int, probes: int, scale: float, least: float):
    """Rows (cell, bi, bj, part, own, rep, n, v) sorted by group -> (rep, links, label): what each batch adds."""

    def count(b: pa.RecordBatch):
        cell, bi, bj, part, own, rep, n = (np.asarray(b.column(c).combine_chunks() if isinstance(b.column(c), pa.ChunkedArray) else b.column(c)) for c in range(7))
        vectors = b.column(7)
        out_rep, out_n, out_lab = [], [], []
        for at, x in _matrix(vectors):
            c, r, w = cell[at], rep[at], n[at]
            key = np.stack([c, bi[at].astype(np.int64), bj[at].astype(np.int64)])
            group = np.cumsum(np.concatenate([[0], (key[:, 1:] != key[:, :-1]).any(0)]))
            i, j = _near_pairs(x, group, own[at], part[at], (bi != bj)[at], least)
            if not len(i):
                continue
            # the pair counts only where it meets first: in the smallest cell that one owns and the other has or visits
            who, first, back = np.unique(r, return_index=True, return_inverse=True)
            a, z = back[i], back[j]
            used = np.unique(np.concatenate([a, z]))
            place = np.full(len(who), -1)
            place[used] = np.arange(len(used))
            mine, seen = cells(x[first[used]], tables, probes, scale)
            least_cell = np.full(len(i), np.iinfo(np.int64).max)
            for lo in range(0, len(i), 4096):
                p, q = place[a[lo : lo + 4096]], place[z[lo : lo + 4096]]
                for t in range(tables):
                    op, oq = mine[p, t], mine[q, t]
                    met = np.where((op == oq) | (seen[q, t] == op[:, None]).any(1), op, np.iinfo(np.int64).max)
                    met = np.minimum(met, np.where((seen[p, t] == oq[:, None]).any(1), oq, np.iinfo(np.int64).max))
                    least_cell[lo : lo + 4096] = np.minimum(least_cell[lo : lo + 4096], met)
            here = (c[i] == least_cell).astype(np.int64)
            total = np.bincount(a, here * w[j], len(who)) + np.bincount(z, here * w[i], len(who))
            lab = _labels(a, z, len(who))
            out_rep.append(who[used])
            out_n.append(total[used].astype(np.int64))
            out_lab.append(who[lab[used]])
        if out_rep:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(o)) for o in (out_rep, out_n, out_lab)], ["rep", "links", "label"])

    def run(batches):
        held = None
        for b in batches:
            t = pa.Table.from_batches([b] if held is None else [held, b]).combine_chunks()
            if not t.num_rows:
                continue
            b = t.to_batches()[0]
            # the last group may go on in the next batch
            last = [b.column(c)[b.num_rows - 1].as_py() for c in range(3)]
            same = np.logical_and.reduce([np.asarray(b.column(c)) == last[c] for c in range(3)])
            cut = int(np.flatnonzero(same)[0])
            held = b.slice(cut)
            if cut:
                yield from count(pa.Table.from_batches([b.slice(0, cut)]).combine_chunks().to_batches()[0])
        if held is not None and held.num_rows:
            yield from count(pa.Table.from_batches([held]).combine_chunks().to_batches()[0])

    return run


def near(vectors: DataFrame, key: str = "vec_id", vector: str = "embedding", least: float = LEAST, tables: int = TABLES, probes: int = PROBES, scale: float = SCALE, block: int = BLOCK) -> DataFrame:
    """(key, n_links, component_id, kept) for every row of vectors."""
    kind = vectors.schema[key].dataType.simpleString()
    v = F.col(vector)
    usable = F.col(key).isNotNull() & v.isNotNull() & F.forall(v, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))) & F.exists(v, lambda c: c != 0)
    rows = vectors.select(F.col(key).alias("id"), v.alias("v"), F.xxhash64(v).alias("h1"), F.xxhash64(F.lit("again"), v).alias("h2"), F.coalesce(usable, F.lit(False)).alias("ok"))
    sets = keep(rows.where("ok").groupBy("h1", "h2").agg(F.min("id").alias("rep"), F.count("*").alias("n"), F.first("v").alias("v")))
    sent = keep(sets.select("rep", "v").repartition("rep").mapInArrow(_emit(tables, probes, scale), f"cell long, rep {kind}, own boolean"))
    busy = sent.groupBy("cell").agg(F.count("*").alias("m"), F.max("own").alias("some")).where("some and m > 1")
    busy = keep(busy.select("cell", F.ceil(F.col("m") / block).cast("int").alias("nb")))
    met = sent.join(busy, "cell")
    mine = F.pmod(F.xxhash64("rep"), F.col("nb")).cast("int")
    met = met.withColumn("part", mine).withColumn("j", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)))
    met = met.select("cell", F.least("part", "j").alias("bi"), F.greatest("part", "j").alias("bj"), "part", "own", "rep")
    work = met.join(sets.select("rep", "n", "v"), "rep").select("cell", "bi", "bj", "part", "own", "rep", "n", "v")
    work = work.repartition("cell", "bi", "bj").sortWithinPartitions("cell", "bi", "bj", "rep")
    found = keep(work.mapInArrow(_links(tables, probes, scale, least), f"rep {kind}, links long, label {kind}"))
    forget(sent, busy)
    linked = found.groupBy("rep").agg(F.sum("links").alias("links"))
    joined = components(found, "rep", "label")
    of = sets.select("h1", "h2", "rep", "n").join(linked, "rep", "left").join(joined, F.col("rep") == F.col("node"), "left")
    of = of.select("h1", "h2", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "rep").alias("c"))
    out = rows.select("id", "h1", "h2", "ok").join(of, ["h1", "h2"], "left")
    out = out.select(F.col("id").alias(key), F.when(F.col("ok"), F.col("n_links")).otherwise(0).alias("n_links"), F.when(F.col("ok"), F.col("c")).otherwise(F.col("id")).alias("component_id"))
    return out.withColumn("kept", F.col(key).eqNullSafe(F.col("component_id")))


def query(spark, sf_dir: str) -> DataFrame:
    from rangekeep.llm._shared import table

    return near(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))
