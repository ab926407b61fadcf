"""Baselines on a tiny plane where every answer can be counted."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from rangekeep.baselines import dyadic, qdigest, sketch, wavelet
from rangekeep.functions.tables import DyadicCover
from rangekeep.plans import workloads as W

POINTS = [(x, y, (x * 7 + y * 3) % 11 + 1) for x, y in itertools.product(range(8), range(4)) if (x + y) % 3]
BOXES = [(0, 0, 1, 6, 0, 3), (1, 0, 0, 8, 0, 4), (2, 0, 3, 4, 2, 3), (2, 1, 5, 8, 0, 1), (3, 0, 2, 2, 0, 4)]


@pytest.fixture(scope="module")
def plane(spark):
    return spark.createDataFrame(POINTS, "x bigint, y bigint, w bigint").cache()


def truth():
    return {q: sum(w for x, y, w in POINTS for b in BOXES if b[0] == q and b[2] <= x < b[3] and b[4] <= y < b[5]) for q in {b[0] for b in BOXES}}


def answers(df):
    return {r.query_id: r.est for r in df.collect()}


def test_full_transform_is_exact(spark, plane):
    c, boxes = wavelet.build(plane, "x", "y", "w", 3, 2), W.frame(spark, BOXES)
    for method in ("overlap", "dyadic"):
        got = answers(wavelet.query(c, boxes, 3, 2, method))
        # a query whose box is empty has no dyadic piece
        assert all(got.get(q, 0) == pytest.approx(v) for q, v in truth().items())
    energy = c.agg(F.sum(F.col("c") * F.col("c"))).first()[0]
    assert energy == pytest.approx(sum(w * w for *_, w in POINTS))


def test_digest_bounds_and_mass(spark, plane):
    boxes = W.frame(spark, BOXES)
    n = qdigest.build_2d(plane, "x", "y", "w", 3, 2, 0.1)
    assert n.agg(F.sum("units")).first()[0] == sum(w for *_, w in POINTS)
    lo, mid, hi = (answers(qdigest.query(n, boxes, k)) for k in ("lower", "share", "upper"))
    assert all(lo[q] - 1e-9 <= t <= hi[q] + 1e-9 and lo[q] <= mid[q] <= hi[q] for q, t in truth().items())
    fine = answers(qdigest.query(qdigest.build_2d(plane, "x", "y", "w", 3, 2, 0.0), boxes))
    assert all(fine[q] == pytest.approx(t) for q, t in truth().items())
    one = qdigest.build_1d(plane, "x", "w", 3, 0.05)
    assert one.agg(F.sum("units")).first()[0] == sum(w for *_, w in POINTS)
    assert qdigest.fit_share(plane, "x", "y", "w", 3, 2, 9).count() <= 9


def test_sketch_is_near_with_room(spark, plane):
    boxes = W.frame(spark, BOXES)
    s = 3 * 4 * 3 * 4000
    got = answers(sketch.query(sketch.build(plane, "x", "y", "w", 3, 2, s), boxes, 3, 2, s))
    assert all(got[q] == pytest.approx(t) for q, t in truth().items())


def test_covers(spark):
    df = spark.createDataFrame([(a, b) for a in range(17) for b in range(a, 17)], "a bigint, b bigint")
    for r in df.select("a", "b", dyadic.cover(F.col("a"), F.col("b"), 4).alias("c")).collect():
        cells = [v for p in r.c for v in range(p.k << p.l, (p.k + 1) << p.l)]
        assert sorted(cells) == list(range(r.a, r.b)) and len(cells) == len(set(cells))
        assert sorted((p.l, p.k) for p in r.c) == sorted(DyadicCover.func().eval(r.a, r.b, 4)) if hasattr(DyadicCover, "func") else True


def test_exact_forms_agree(spark, plane):
    boxes = W.frame(spark, BOXES)
    for cells in ((0, 0), (3, 2)):
        got = {r.query_id: r.exact for r in W.exact_boxes(plane, boxes, "x", "y", "w", *cells).collect()}
        assert got == truth()


def test_uniform_area_is_disjoint():
    b = W.uniform_area(100, 60, 5, 8, 0.3)
    assert len(b) == 40
    for p, q in itertools.combinations(b, 2):
        assert p[0] != q[0] or p[3] <= q[2] or q[3] <= p[2] or p[5] <= q[4] or q[5] <= p[4]


@pytest.mark.parametrize(("bx", "by"), [(12, 4), (3, 11), (5, 5), (1, 1)])
def test_wavelet_top_is_the_largest_of_all(spark, bx, by):
    """Blocks on either axis, ties by number, and the count of all coefficients."""
    rng = np.random.default_rng(bx)
    rows = [(int(a), int(b), int(c)) for a, b, c in zip(rng.integers(0, 1 << bx, 400), rng.integers(0, 1 << by, 400), rng.integers(1, 4, 400), strict=True)]
    points = spark.createDataFrame(rows, "x bigint, y bigint, w bigint")
    every = wavelet.build(points, "x", "y", "w", bx, by)
    got = wavelet.top(points, "x", "y", "w", bx, by, 60)
    tell = lambda df: sorted((r.ix, r.iy, r.signed, r.c) for r in df.collect())
    assert tell(got.where("ix >= 0")) == tell(wavelet.largest(every, 60))
    assert got.where("ix < 0").first().signed == every.count()


def test_wavelet_of_named_coefficients(spark):
    """Only what the boxes feel is made, and answers stay those of all coefficients."""
    points = spark.createDataFrame([(i * 37 % 256, i * 11 % 64, 1 + i % 5) for i in range(500)], "x bigint, y bigint, w bigint")
    boxes = spark.createDataFrame([(0, 0, 3, 90, 5, 40), (1, 0, 17, 18, 0, 64)], "query_id int, rect_id int, x_lo bigint, x_hi bigint, y_lo bigint, y_hi bigint")
    some, every = wavelet.build(points, "x", "y", "w", 8, 6, wavelet.felt(boxes, 8, 6)), wavelet.build(points, "x", "y", "w", 8, 6)
    tell = lambda df: {r.query_id: round(r.est, 6) for r in wavelet.query_all(df, boxes, 8, 6).collect()}
    assert tell(some) == tell(every) and some.count() < every.count()


def test_plane_queries_keep_the_bits_of_their_sql(spark, duck, tmp_path):
    """Keys beyond the SQL's 15 and 10 bits, as larger tables have them."""
    from conftest import same

    from rangekeep import registry

    rows = [(i * 7919 % 90_000, i * 31 % 5_000, 100.0 + i % 70) for i in range(300)]
    spark.createDataFrame(rows, "l_partkey bigint, l_suppkey bigint, l_extendedprice double").coalesce(1).write.parquet(str(tmp_path / "lineitem.parquet"))
    for name in ("haar_coeffs", "haar_top", "haar_counters", "qdigest2d_nested", "sketch_counters", "haar_full_equals_exact"):
        assert same(registry.queries()[name](spark, str(tmp_path)).toPandas(), duck(registry.oracle_sql()[name], tmp_path)), name


def test_sketch_of_blocks(spark):
    """Points of many blocks, some keys in two rows: all counters against plain hashes, none shuffled as rectangles, and boxes ask for theirs alone."""
    import hashlib

    points = [(i * 7919 % 4_000, i * 31 % 3_000, 1 + i % 5) for i in range(60)] * 2
    s, bits, want = 3 * 13 * 13 * 4, (12, 12), {}
    u = lambda tag, *key: int(hashlib.md5("|".join(map(str, (tag, 1, *key))).encode()).hexdigest()[:13], 16) / (1 << 52)
    for x, y, w in points:
        for at in ((lx, ly, row, x >> lx, y >> ly) for lx in range(13) for ly in range(13) for row in range(3)):
            key = (*at[:3], int(u("bucket", *at) * 4))
            want[key] = want.get(key, 0) + (w if u("sign", *at) < 0.5 else -w)
    df = spark.createDataFrame(points, "x bigint, y bigint, w bigint")
    every = sketch.build(df, "x", "y", "w", *bits, s)
    # one exchange for points, one for counters
    assert every._jdf.queryExecution().executedPlan().toString().count("Exchange") == 2
    assert {tuple(r)[:4]: r.counter for r in every.collect()} == want
    boxes = spark.createDataFrame([(0, 0, 100, 900, 7, 2_000), (1, 0, 2_000, 2_001, 0, 4_096)], W.BOX)
    some = sketch.build(df, "x", "y", "w", *bits, s, boxes=boxes)
    got = {tuple(r)[:4]: r.counter for r in some.collect()}
    assert len(got) < len(want) and got.items() <= want.items()
    assert answers(sketch.query(some, boxes, *bits, s)) == answers(sketch.query(every, boxes, *bits, s))


def test_wavelet_answers_by_equality_are_those_of_all_boxes(spark):
    points = spark.createDataFrame([(i * 37 % 256, i * 11 % 64, 1 + i % 5) for i in range(500)], "x bigint, y bigint, w bigint")
    boxes = spark.createDataFrame([(0, 0, 3, 90, 5, 40), (1, 0, 17, 18, 0, 64), (1, 1, 100, 256, 60, 64), (2, 0, 250, 251, 1, 2)], W.BOX)
    some = wavelet.largest(wavelet.build(points, "x", "y", "w", 8, 6), 40)
    assert answers(wavelet.query_all(some, boxes, 8, 6)) == pytest.approx(answers(wavelet.query(some, boxes, 8, 6)))


def test_transform_in_parts_is_that_of_rows(spark, monkeypatch):
    """Keys within and far beyond the bits, some in two rows, cut into many parts: every coefficient as summed row by row, points shuffled once."""
    rng = np.random.default_rng(3)
    rows = [(int(a), int(b), int(c)) for a, b, c in zip(rng.integers(0, 1 << rng.integers(3, 13, 300)), rng.integers(0, 1 << rng.integers(2, 9, 300)), rng.integers(-3, 4, 300), strict=True)]
    points = spark.createDataFrame(rows + rows[:50], "x bigint, y bigint, w bigint")
    tell = lambda df: sorted((r.ix, r.iy, r.signed, r.c) for r in df.collect())
    for bits in ((6, 4), (4, 7), (13, 9)):
        want = tell(wavelet._exploded(points, "x", "y", "w", *bits))
        for share in (1 << 15, 40, 5, 1):
            monkeypatch.setattr(wavelet, "BLOCK_POINTS", share)
            got = wavelet.build(points, "x", "y", "w", *bits)
            assert tell(got) == want
        plan = got._jdf.queryExecution().optimizedPlan().toString()
        # contributions are made of folded points alone, all others in a task's memory
        assert plan.count("FlatMapGroupsInArrow") == 1 and plan.count("Generate explode") == 2


def test_nested_digest_in_stretches_is_that_of_nodes(spark, monkeypatch):
    """Every node's digest against a plain count, with x and y beyond their bits and any width of a stretch; points are shuffled, not their copies."""
    rng = np.random.default_rng(5)
    rows = [(int(a), int(b), int(c)) for a, b, c in zip(rng.integers(0, 200, 300), rng.integers(0, 70, 300), rng.integers(1, 9, 300), strict=True)]
    least, want = 0.02 * sum(r[2] for r in rows), []
    for kx in range(7):
        now = {}
        for x, y, w in rows:
            now[x >> kx, y] = now.get((x >> kx, y), 0) + w
        for ky in range(6):
            stay = {k: v for k, v in now.items() if ky == 5 or v >= least}
            want += [(kx, ky, *k, v) for k, v in stay.items()]
            up = {}
            for (x, y), v in now.items():
                if (x, y) not in stay:
                    up[x, y >> 1] = up.get((x, y >> 1), 0) + v
            now = up
    points = spark.createDataFrame(rows, "x bigint, y bigint, w bigint")
    for share in (1 << 15, 100, 20, 1):
        monkeypatch.setattr(qdigest, "STRETCH_POINTS", share)
        got = qdigest.build_2d_nested(points, "x", "y", "w", 6, 5, 0.02)
        assert sorted(map(tuple, got.collect())) == sorted(want), share
    monkeypatch.setattr(qdigest, "STRETCH_POINTS", 1 << 15)
    assert "Generate" not in qdigest.build_2d_nested(points, "x", "y", "w", 6, 5, 0.02)._jdf.queryExecution().optimizedPlan().toString()


def test_sketch_hashes_in_memory_are_those_of_columns(spark, monkeypatch):
    """Rectangles of every number of digits: bucket and sign by arrays equal those of _place(), and no rectangle leaves its task."""
    rows = [(lx, ly, row, kx, ky) for lx in (0, 9, 12) for ly in (3, 10) for row in (0, 2) for kx in (0, 7, 10, 99, 12345, 10**9 - 1, 10**10, 2**62) for ky in (0, 9, 100, 65_535, 2**33, 2**62)]
    df = spark.createDataFrame(rows, "lx int, ly int, row int, kx bigint, ky bigint")
    seeds = spark.range(1).select(F.xxhash64(F.lit("bucket"), F.lit(5)), F.xxhash64(F.lit("sign"), F.lit(5))).first()
    for portable, place in ((True, sketch._portable(5)), (False, sketch._quick(*seeds))):
        want = {tuple(r)[:5]: (r.bucket, r.sign) for r in df.withColumns(dict(zip(("bucket", "sign"), sketch._place(5, 1000, portable), strict=True))).collect()}
        for row in (0, 2):
            some = [r for r in rows if r[2] == row]
            lx, ly, _, kx, ky = np.array(some, np.int64).T
            bucket, sign = place(1000, row, lx, ly, kx, ky)
            assert [want[r] for r in some] == list(zip(bucket.tolist(), sign.tolist(), strict=True))
    points = spark.createDataFrame([(i * 7919 % 4_000, i * 31 % 3_000, 1 + i % 5) for i in range(200)], "x bigint, y bigint, w bigint")
    tell = lambda **how: sorted(map(tuple, sketch.build(points, "x", "y", "w", 12, 12, 3 * 13 * 13 * 4, **how).collect()))
    whole = tell(portable=False)
    monkeypatch.setattr(sketch, "AT_ONCE", 100)
    assert tell(portable=False) == whole
    assert "Generate" not in sketch.build(points, "x", "y", "w", 12, 12, 2000)._jdf.queryExecution().optimizedPlan().toString()


def test_wavelet_answers_where_weight_times_area_passes_63_bits(spark):
    points = spark.createDataFrame([(0, 0, 1 << 45), (1 << 19, 1 << 19, 1 << 44)], "x bigint, y bigint, w bigint")
    boxes = spark.createDataFrame([(0, 0, 0, 1 << 20, 0, 1 << 20), (1, 0, 0, 1 << 19, 0, 1 << 19)], W.BOX)
    made = wavelet.build(points, "x", "y", "w", 20, 20)
    assert answers(wavelet.query(made, boxes, 20, 20)) == {0: 3 * 2.0**44, 1: 2.0**45}
