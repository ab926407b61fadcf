"""Invariants of samples on the given tables and on small edge cases."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rangekeep.operators import kdtree
from rangekeep.operators import metrics as M
from rangekeep.operators import structures as S
from rangekeep.operators import twopass as T
from rangekeep.operators.estimate import count_bounds
from rangekeep.operators.ipps import local_threshold, threshold, with_inclusion
from rangekeep.operators.keys import keyed


@pytest.fixture(scope="module")
def docs(spark, data):
    d = spark.read.parquet(f"{data}/documents.parquet")
    return keyed(d, ["doc_id"], "n_chars", carry=["lang", "source"]).cache()


def frame(spark, weights):
    return keyed(spark.createDataFrame([(i, float(w)) for i, w in enumerate(weights)], "id bigint, w double"), ["id"], "w")


@pytest.mark.parametrize("weights,s", [([5, 5, 5, 5], 2), ([100, 1, 1, 1, 1], 2), ([1, 2, 3], 5), ([0, 0, 4], 1), ([7] * 9, 9), ([1] * 10, 1)])
def test_thresholds(spark, weights, s):
    k = frame(spark, weights)
    th = threshold(k, s)
    live = [w for w in weights if w > 0]
    p = [min(1, w / th.tau) if th.tau else 1 for w in live]
    assert sum(p) == pytest.approx(min(s, len(live)))
    it = threshold(k, s, "iterate")
    assert it.tau == pytest.approx(th.tau)
    assert local_threshold(np.array(live, float), float(sum(live)), s) == pytest.approx(th.tau) or len(live) <= s
    out = S.varopt(k, s).rows.collect()
    assert len(out) == min(s, len(live)) and sum(r.adj_weight for r in out) == pytest.approx(sum(live))


def test_bad_weights(spark):
    rows = spark.createDataFrame([(1, 2.0), (2, -1.0), (3, None), (1, 3.0)], "id bigint, w double")
    assert {r.id: r.units for r in keyed(rows, ["id"], "w", on_bad="drop").collect()} == {1: 5}
    with pytest.raises(Exception, match="weight"):
        keyed(rows, ["id"], "w").collect()
    empty = keyed(rows.limit(0), ["id"], "w")
    assert threshold(empty, 3).n == 0 and S.varopt(empty, 3).rows.count() == 0


@pytest.mark.parametrize("make,nodes", [
    (lambda k: S.sample_disjoint(k, 40, ["source"]), [["source"]]),
    (lambda k: S.sample_hierarchy(k, 40, ["lang", "source"]), [["lang"], ["lang", "source"]]),
    (lambda k: T.two_pass(k, 40, T.Hierarchy(["lang", "source"])), []),
    (lambda k: T.two_pass(k, 40, T.Product(["doc_id"])), []),
])
def test_sizes_heavy_and_nodes(docs, make, nodes):
    out = make(docs)
    rows = out.rows.collect()
    assert len(rows) == len({r.hk for r in rows}) == 40
    assert sum(r.adj_weight for r in rows) == pytest.approx(out.th.total)
    inc = with_inclusion(docs, out.th.tau)
    assert {r.hk for r in inc.where("is_heavy").collect()} <= {r.hk for r in rows}
    for by in nodes:
        assert M.group_discrepancy(inc, out.rows, by).agg(F.max("off")).first()[0] < 1 + 1e-6


def test_order_bounds_and_buckets(spark, docs):
    k = docs.withColumn("bucket", F.floor(F.col("doc_id") / 40))
    a, b = S.sample_order(k, 30, ["doc_id"]), S.sample_order_bucketed(k, 30, ["doc_id"], "bucket")
    assert {r.hk for r in a.rows.collect()} == {r.hk for r in b.rows.collect()}
    r = M.prefix_discrepancy(with_inclusion(k, a.th.tau), a.rows, ["doc_id"]).first()
    assert r.prefix < 1 and r.interval < 2


def test_inclusion_over_seeds(docs):
    """Each key's share over many seeds is its probability, for blind and aware samples."""
    th = threshold(docs, 20)
    p = {r.hk: r.p for r in with_inclusion(docs, th.tau).collect()}
    from rangekeep.functions import UNIT
    from rangekeep.operators import local

    keys = sorted(p, key=int)
    t = np.array([min(UNIT, int(p[k] * UNIT + 0.5)) for k in keys])
    light = np.flatnonzero((t > 0) & (t < UNIT))
    runs, rng, hits = 4000, np.random.default_rng(1), np.zeros(len(keys))
    for _ in range(runs):
        got, left, mass = local.chain(np.zeros(len(light), np.int64), t[light], rng.random(len(light)))
        hits[light[got]] += 1
        hits[light[left[mass * 2 >= UNIT]]] += 1
    want = t[light] / UNIT
    z = (hits[light] / runs - want) / np.sqrt(want * (1 - want) / runs)
    assert np.abs(z).max() < 5


def test_two_pass_matches_cells(docs):
    """Order cells: prefixes of the two-pass sample stay close, and any guide gives the size."""
    for guide in ("poisson", "varopt", "reservoir"):
        out = T.two_pass(docs, 25, T.Order("doc_id"), guide=guide)
        assert out.rows.count() == 25
        r = M.prefix_discrepancy(with_inclusion(docs, out.th.tau), out.rows, ["doc_id"]).first()
        assert r.interval < 4


def test_kd_tree_balances_and_locates():
    rng = np.random.default_rng(0)
    pts, m = [rng.integers(0, 50, 400), rng.integers(0, 50, 400)], rng.random(400)
    tree, leaf = kdtree.build(pts, m, leaf_mass=m.sum() / 16)
    assert (tree.locate(pts) == leaf).all() and max(tree.mass[i] for i in tree.leaves()) <= m.sum() / 16 + m.max() * 8
    same = [np.zeros(5, int), np.arange(5)]
    tree, leaf = kdtree.build(same, np.ones(5))
    assert len(set(leaf)) == 5
    assert len(set(kdtree.build([np.zeros(4, int)] * 2, np.ones(4))[1])) == 1
    boxes = kdtree.leaf_boxes(kdtree.build(pts, m, depth=3)[0], [0, 0], [50, 50])
    assert sum((b[0][1] - b[0][0]) * (b[1][1] - b[1][0]) for b in boxes.values()) == 2500
    levels = np.array([[0, 0], [0, 1], [1, 2], [1, 3], [2, 4]])
    tree, leaf = kdtree.build([levels], np.ones(5))
    assert len(set(leaf)) == 5 and (tree.locate([levels]) == leaf).all()


def test_count_bounds_hold_the_count():
    lo, hi = count_bounds(np.array([0, 1, 10, 100]), 0.05)
    assert lo[0] == 0 and hi[0] == pytest.approx(np.log(40), rel=1e-6)
    assert (lo <= [0, 1, 10, 100]).all() and (hi >= [0, 1, 10, 100]).all() and lo[3] > 75 and hi[3] < 130


def test_bound_size_and_gain(docs):
    """A prefix's sum is off by no more than the count's deviation times the threshold; sizes and gains in plain numbers."""
    out = S.sample_order(docs, 30, ["doc_id"])
    inc = with_inclusion(docs, out.th.tau)
    bound = M.error_bound(M.prefix_discrepancy(inc, out.rows, ["doc_id"]).first().prefix, out.th.tau)
    true = {r.doc_id: r.units for r in docs.select("doc_id", "units").collect()}
    got = {r.doc_id: r.adj_weight for r in out.rows.select("doc_id", "adj_weight").collect()}
    off = np.cumsum([got.get(k, 0.0) - true[k] for k in sorted(true)])
    assert 0 < np.abs(off).max() <= bound * (1 + 1e-6)
    assert M.size_bytes(2700) == 32_400 and M.size_bytes(100, axes=1) == 800
    assert M.gain(1.0, 4.0) == 0.25 and np.isnan(M.gain(1.0, 0.0))


def test_broadcast_is_measured(spark):
    """A side is sent whole only if few rows and few bytes are counted in it."""
    from rangekeep.sources.shared import small

    def sent(df):
        return "broadcast" in df._jdf.queryExecution().logical().toString().lower()

    wide = spark.range(10).select("id", F.repeat(F.lit("x"), 1000).alias("t"), F.array("id").alias("a"))
    assert sent(small(wide)) and not sent(small(wide, most=9)) and not sent(small(wide, most_bytes=9_000)) and sent(small(spark.range(0)))


def test_every_depth_of_deep_hierarchies(spark, data):
    """Nodes below the fourth path element and at every prefix length get the floor or ceiling of their mass."""
    from rangekeep.plans import sampling_queries as Q
    from rangekeep.sources.shared import keep

    k, cols = Q.url_set(spark, data)
    deepest = k.agg(F.max(F.size("path"))).first()[0]
    assert len(cols) == deepest > 4
    sets = [(k, S.sample_hierarchy(k, 20, cols), [F.slice("path", 1, d) for d in range(1, deepest + 1)])]
    k, cols = Q.prefix_set(spark, data)
    most = k.agg(F.max("code")).first()[0].bit_length()
    assert len(cols) > 4 and k.select(cols[-1]).distinct().count() < k.count()
    sets += [(k, S.sample_hierarchy(k, 20, cols), [F.shiftright("code", n) for n in range(most)])]
    for k, out, nodes in sets:
        chosen, inc = keep(out.rows), keep(with_inclusion(k, out.th.tau))
        assert chosen.count() == 20
        for n in nodes:
            assert M.group_discrepancy(inc.withColumn("node", n), chosen, ["node"]).agg(F.max("off")).first()[0] < 1 + 1e-6


def test_kd_nodes_hold_one_unit(spark):
    """Far more units than nodes cut in Spark: every last node holds one unit at most, and every node's count is floor or ceiling."""
    from rangekeep.operators import product

    rng = np.random.default_rng(3)
    k = spark.createDataFrame([(i, int(x), int(y), float(w)) for i, (x, y, w) in enumerate(zip(rng.permutation(4000), rng.permutation(4000), rng.integers(50, 100, 4000), strict=True))], "id bigint, x bigint, y bigint, w double")
    out, parts, top = product._product(keyed(k, ["id"], "w", carry=["x", "y"]), 1000, ["x", "y"], part_rows=300)
    chosen = out.rows.select("hk", "is_heavy").collect()
    assert len(chosen) == len({r.hk for r in chosen}) == 1000 and 4 <= top < 9
    assert parts.groupBy("node", "way").agg((F.sum("ticks") / float(1 << 40)).alias("m")).agg(F.max("m")).first()[0] <= 1
    assert product.node_counts(parts, top, out.rows).agg(F.max("off")).first()[0] < 1 + 1e-6


def test_a_tree_for_tasks_is_arrays():
    """A pickled tree finds the same leaves for axes of every kind and is far smaller than its lists."""
    import pickle

    import numpy as np

    from rangekeep.operators import kdtree

    rng = np.random.default_rng(3)
    n = 4_000
    axes = [rng.integers(0, 1 << 60, n), kdtree.Codes.of(rng.integers(0, 1 << 16, n)), np.stack([rng.integers(0, 5, n), rng.integers(0, 50, n)], axis=1)]
    tree, leaf = kdtree.build(axes, rng.random(n), depth=9)
    sent = pickle.loads(pickle.dumps(tree))
    assert (sent.locate(axes) == tree.locate(axes)).all() and (tree.locate(axes) == leaf).all()
    wide, _ = kdtree.build([rng.random(n)], np.ones(n))
    assert not hasattr(sent, "axis") and len(pickle.dumps(wide)) < 60 * len(wide.axis)
