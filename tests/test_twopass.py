"""The two-pass sampler over thousands of seeds: every key's share is its probability, pairs keep the bounds, cells hold."""

import numpy as np
import pyarrow as pa
import pytest

from rangekeep.functions import UNIT
from rangekeep.operators import kdtree, local
from rangekeep.operators import twopass as T
from rangekeep.operators.metrics import check_aggregate

P = np.array([0.01, 0.02, 0.5, 0.6, 0.9, 0.3, 0.2, 0.8])


def hashes(rng, n):
    return rng.integers(-(1 << 63), (1 << 63) - 1, n)


def batches(cols: dict, at: np.ndarray, parts: int):
    """The rows `at` of columns as record batches."""
    return [pa.RecordBatch.from_pydict({k: pa.array(v[i]) for k, v in cols.items()}) for i in np.array_split(at, parts) if len(i)]


def tables(out):
    out = list(out)
    return pa.Table.from_batches(out) if out else None


def draw(structure, cols: dict, tasks: list[np.ndarray], parts: int) -> tuple[np.ndarray, pa.Table]:
    """What two_pass() does with a fitted structure, without Spark: (numbers of settled keys, undecided rows of all cells)."""
    passed = pa.concat_tables([t for at in tasks if (t := tables(T._cell_pass(structure, 0)(iter(batches(cols, at, parts))))) is not None])
    open_ = passed.filter(pa.array(np.asarray(passed.column("ticks")) < UNIT)).sort_by([("cell", "ascending"), ("hk", "ascending")])
    merged = tables(T._cell_pass(None, 1)(iter(open_.to_batches())))
    done = [np.asarray(passed.column("i"))[np.asarray(passed.column("ticks")) >= UNIT]]
    if merged is None:
        return done[0], passed.slice(0, 0)
    full = np.asarray(merged.column("ticks")) >= UNIT
    done.append(np.asarray(merged.column("i"))[full])
    return np.concatenate(done), merged.filter(pa.array(~full)).sort_by([("cell", "ascending"), ("hk", "ascending")])


class Replicates:
    """Every replicate is a cell of its own, so that one pass draws all of them."""

    columns = ["replicate"]

    def locate(self, cols):
        return cols[0]


def test_cell_pass_keeps_probabilities(monkeypatch):
    """20,000 fresh draws of one cell whose keys come in several batches of two tasks."""
    monkeypatch.setattr("rangekeep.streaming.reservoir.gathered.__defaults__", (1,))
    runs, n = 20_000, len(P)
    rng = np.random.default_rng(1)
    t = np.floor(P * UNIT + 0.5).astype(np.int64)
    cols = {"hk": np.array([str(i % n) for i in range(runs * n)]), "ticks": np.tile(t, runs), "h": hashes(rng, runs * n), "cell": np.zeros(runs * n, np.int64),
            "i": np.arange(runs * n), "replicate": np.repeat(np.arange(runs), n)}
    key = np.arange(runs * n) % n
    # three batches a task, cut across the keys: a cell's key is carried from one to the next
    first, second = [np.concatenate([np.flatnonzero(key == k) for k in ks]) for ks in ((0, 1, 2, 3, 4), (5, 6, 7))]
    done, left = draw(Replicates(), cols, [first, second], 3)
    hits = np.zeros((runs, n))
    hits[done // n, done % n] = 1
    i, mass = np.asarray(left.column("i")), np.asarray(left.column("ticks"))
    hits[i // n, i % n] = mass / UNIT
    z = (hits.mean(0) - P) / np.sqrt(P * (1 - P) / runs)
    assert np.abs(z).max() < 4.5, z
    assert np.allclose(hits.sum(1), P.sum(), atol=1e-9)
    pairs = [[a, b] for a in range(n) for b in range(a)]
    assert all(check_aggregate(hits, P, pairs, z=4.5).values())


def data(seed=3, n=60):
    rng = np.random.default_rng(seed)
    w = rng.integers(1, 40, n)
    t = np.floor(w / w.sum() * 9 * UNIT + 0.5).astype(np.int64)
    a, b, c = rng.integers(0, 3, n), rng.integers(0, 5, n), rng.integers(0, 9, n)
    return rng, t, {"x": rng.integers(0, 64, n), "y": rng.integers(0, 64, n), "a": a, "b": a * 10 + b, "c": np.array([f"{i}-{j}" for i, j in zip(b, c, strict=True)])}


SHAPES = {
    "product": lambda: T.Product(["x", "y"]),
    "codes": lambda: T.Product([T.Prefixes("x"), "y"]),
    "levels": lambda: T.Product([T.Levels(("a", "b", "c")), "x"]),
    "order": lambda: T.Order("x"),
    "disjoint": lambda: T.Disjoint("b"),
    "linear": lambda: T.Hierarchy(["a", "b", "c"], "linear"),
    "ancestors": lambda: T.Hierarchy(["a", "b", "c"], "ancestors"),
}


@pytest.mark.parametrize("shape", sorted(SHAPES))
def test_shares_over_seeds(shape, runs=2500):
    """A guide is fitted once; 2,500 seeds of both passes and the last step, with two tasks of three batches."""
    rng, t, cols = data()
    n, p = len(t), t / UNIT
    guide = np.sort(rng.choice(n, 20, replace=False))
    structure = SHAPES[shape]()
    structure.fit([cols[c][guide] for c in structure.columns], p[guide] * 3)
    cell = structure.locate([cols[c] for c in structure.columns])
    hits = np.zeros((runs, n))
    for r in range(runs):
        h = hashes(rng, n)
        rows = {**cols, "hk": np.array([str(i) for i in range(n)]), "ticks": t, "h": h, "cell": np.zeros(n, np.int64), "i": np.arange(n)}
        done, left = draw(structure, rows, [np.arange(35), np.arange(35, n)], 3)
        hits[r, done] = 1
        i, at, ticks = (np.asarray(left.column(c)) for c in ("i", "cell", "ticks"))
        more = structure.finish(at, ticks, lambda level, q, h=h, i=i: local.fresh(h[i][q], 2 + level))
        hits[r, i[np.asarray(more, int)]] = 1
    assert (hits.sum(1) == round(p.sum())).all()
    z = (hits.mean(0) - p) / np.sqrt(p * (1 - p) / runs)
    assert np.abs(z).max() < 4.5, z
    pairs = [[a, b] for a in range(0, n, 3) for b in range(1, n, 7) if a != b]
    assert all(check_aggregate(hits, p, pairs, z=4.5).values())
    # every cell and every node over cells (or prefix of cells) holds the floor or the ceiling of its mass
    up, many = structure.up(), int(cell.max()) + 1
    inside = np.eye(many if up is None else len(up))[cell]
    if up is None:
        inside = np.cumsum(inside[:, ::-1], 1)[:, ::-1].T  # cells up to each
        inside = np.array([(cell <= c) for c in range(many)], float)
    else:
        for i in range(len(up) - 1, 0, -1):
            inside[:, up[i]] += inside[:, i]
        inside = inside.T
    assert np.abs(hits @ inside.T - inside @ p).max() < 1 + 1e-6


def test_located_as_fitted():
    """Every structure puts a point where its definition says, strings, nulls and unmet values included."""
    guide = [("a", "x"), ("a", "z"), ("c", "x")]
    cols = [np.array([g[i] for g in guide], dtype=object) for i in range(2)]
    points = [("a", "w"), ("a", "x"), ("a", "y"), ("a", "z"), ("a", "~"), ("b", "x"), ("c", "a"), ("c", "x"), ("c", "y"), ("d", "d"), ("", "")]
    at = [np.array([p[i] for p in points], dtype=object) for i in range(2)]
    line = T.Hierarchy(["p", "q"], "linear").fit(cols, None)
    assert line.locate(at).tolist() == [sum(g < p for g in guide) for p in points]
    tree = T.Hierarchy(["p", "q"]).fit(cols, None)
    names = {(): 0, ("a",): 1, ("c",): 2, ("a", "x"): 3, ("a", "z"): 4, ("c", "x"): 5}
    assert tree.locate(at).tolist() == [names[max((p[:d] for d in range(3) if p[:d] in names), key=len)] for p in points]
    assert T._values(pa.array(["b", None])).tolist() == ["b", ""] and T._values(pa.array([3, None])).tolist()[1] < 0
    assert T.Hierarchy(["p"]).fit([np.zeros(0, object)], None).locate([at[0]]).tolist() == [0] * len(points)


def test_code_cuts_are_prefixes():
    rng = np.random.default_rng(5)
    for _ in range(200):
        v, m = rng.integers(0, 1 << 12, int(rng.integers(2, 40))), None
        m = rng.random(len(v)) ** 3
        cut = kdtree.code_cut(v, m)
        if cut is None:
            assert len(set(v.tolist())) == 1
            continue
        low, high = cut
        size = high - low + 1
        assert size & (size - 1) == 0 and low % size == 0 and 0 < ((v >= low) & (v <= high)).sum() < len(v)
        # no prefix splits the mass more evenly than one that this walk could have met
        inside = m[(v >= low) & (v <= high)].sum()
        assert inside <= m.sum() / 2 + 1e-12 or len(set(v[(v >= low) & (v <= high)].tolist())) == 1
    codes = kdtree.Codes.of(rng.integers(0, 1 << 20, 500))
    tree, leaf = kdtree.build([codes, rng.random(500)], np.ones(500), leaf_mass=4.0)
    assert (tree.locate([codes, codes * 0]) >= 0).all() and (kdtree.build([codes], np.ones(500))[0].locate([codes]) == kdtree.build([codes], np.ones(500))[1]).all()


@pytest.mark.parametrize("n,s", [(200_000, 50_000), (400, 60)])
def test_shrink_is_unbiased(n, s):
    """Draws have nothing to do with the order or with each other, at any size."""
    rng = np.random.default_rng(2)
    w = rng.random(n) * 9 + 1
    runs = 40 if n > 1000 else 4000
    hits = np.zeros(n)
    for r in range(runs):
        rows, _ = local.shrink(w, s, hashes(rng, n), r)
        hits[rows] += 1
    from rangekeep.operators.ipps import local_threshold

    p = np.minimum(1, w / local_threshold(w, w.sum(), s))
    inner = (p > 0) & (p < 1)
    z = (hits[inner] / runs - p[inner]) / np.sqrt(p[inner] * (1 - p[inner]) / runs)
    assert np.abs(z).max() < 5.5 and abs(np.corrcoef(z, p[inner])[0, 1]) < 0.2 and abs(z.std() - 1) < 0.15


def test_guide_in_one_scan(spark, data_keys):
    """The one-scan guide holds the exact totals and the threshold of a sort of all keys, for any number of tasks."""
    from rangekeep.operators.ipps import threshold

    for parts in (1, 7):
        g = T.draw_guide(data_keys.repartition(parts), 100, columns=["doc_id"])
        th = threshold(data_keys, 40)
        got = T.threshold_from_guide(np.asarray(g.rows.column("units")), g.total, g.n, 40)
        assert (got.k, got.heavy, got.total, got.n) == (th.k, th.heavy, th.total, th.n) and got.tau == pytest.approx(th.tau, rel=1e-12)
        assert g.rows.num_rows == 100 and g.stands.sum() == pytest.approx(g.total)
    few = T.draw_guide(data_keys.limit(0), 10)
    assert few.rows.num_rows == few.total == few.n == 0


@pytest.fixture(scope="module")
def data_keys(spark, data):
    from rangekeep.operators.keys import keyed
    from rangekeep.sources.shared import keep

    d = spark.read.parquet(f"{data}/documents.parquet")
    return keep(keyed(d, ["doc_id"], "n_chars", carry=["lang", "source"]))


def test_reads_the_keys_twice(spark, data_keys):
    """Two scans of the keys in all jobs of a two-pass sample with the one-scan guide."""
    seen = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            seen.add(b.num_rows)
            yield b

    counted = data_keys.mapInArrow(count, data_keys.schema)
    n = data_keys.where("units > 0").count()
    out = T.two_pass(counted, 30, T.Order("doc_id"))
    assert out.rows.count() == 30 and out.rows.count() == 30
    assert seen.value <= 2 * data_keys.count() and n > 30


def test_blind_samples_are_found_out(spark, data_keys):
    """The counts of nodes that the registered rows report tell an aware sample from a blind one."""
    from rangekeep.operators import structures as S
    from rangekeep.sources.shared import keep

    for shape in (T.Product(["doc_id"]), T.Order("doc_id"), T.Disjoint("source"), T.Hierarchy(["lang", "source"])):
        out, fitted = T._two_pass(data_keys, 40, shape)
        kept = S.Summary(keep(out.rows), out.th, 1, "x")
        assert T.nodes_off(data_keys, kept, fitted)[0] == 0
        bad = [T.nodes_off(data_keys, S.Summary(keep(S.varopt(data_keys, 40, seed=i).rows), out.th, 1, "x"), fitted)[0] for i in range(3)]
        assert sum(bad) > 0, shape


def test_small_and_odd_key_sets(spark, data_keys):
    for s in (1, 5000):
        assert T.two_pass(data_keys, s, T.Product(["doc_id"])).rows.count() == min(s, data_keys.where("units > 0").count())
    assert T.two_pass(data_keys.limit(0), 3, T.Order("doc_id")).rows.count() == 0
    with pytest.raises(ValueError):
        T.two_pass(data_keys, 0, T.Order("doc_id"))
    nulls = data_keys.selectExpr("doc_id", "hk", "units", "CASE WHEN doc_id % 3 = 0 THEN NULL ELSE source END AS source", "CAST(doc_id % 7 AS INT) AS cell")
    for shape in (T.Disjoint("source"), T.Hierarchy(["source"]), T.Product([T.Levels(("source", "doc_id")), T.Prefixes("doc_id")])):
        assert T.two_pass(nulls, 20, shape).rows.count() == 20
