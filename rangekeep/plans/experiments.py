"""The accuracy and cost experiments on the given tables: every method on the same batteries of queries.

Samples and summaries are drawn once a setting and answer all batteries in one join; errors are averaged in Spark, and
only a few rows of them reach the driver.
"""

from __future__ import annotations

import math
import time
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangekeep.baselines import qdigest, sketch, wavelet
from rangekeep.operators import metrics as M
from rangekeep.operators import structures as S
from rangekeep.operators import twopass as T
from rangekeep.plans import planes as P
from rangekeep.plans import workloads as W
from rangekeep.sources.shared import keep

BOX = "setting string, " + W.BOX
ALL = ("aware", "oblivious", "wavelet", "qdigest", "sketch")
#: Queries of a battery, and seeds of a sampler.
QUERIES, SEEDS = 50, 3
#: Samples drawn at once while they are small; a draw is many short jobs. Larger ones have large guides on the driver.
AT_ONCE, SMALL_SAMPLE = 4, 10_000


class Batteries:
    """Boxes of several settings with their true answers; query ids are unique over all settings."""

    def __init__(self, p: P.Plane, parts: dict[str, list[tuple]]):
        rows, first = [], 0
        for setting, boxes in parts.items():
            rows += [(setting, first + b[0], *b[1:]) for b in boxes]
            first += 1 + max((b[0] for b in boxes), default=0)
        self.plane = p
        self.boxes = keep(p.keys.sparkSession.createDataFrame(rows, BOX))
        of = self.boxes.select("setting", "query_id").distinct()
        self.truth = keep(P.truth(p, self.boxes.drop("setting")).join(of, "query_id"))

    def answered(self, points: DataFrame, *by: str) -> DataFrame:
        """(by..., query_id, est) of sampled points (x, y, adj_weight, by...): samples and boxes are a few thousand rows each."""
        hit = (F.col("x") >= F.col("x_lo")) & (F.col("x") < F.col("x_hi")) & (F.col("y") >= F.col("y_lo")) & (F.col("y") < F.col("y_hi"))
        return points.join(F.broadcast(self.boxes), hit).groupBy(*by, "query_id").agg(F.sum("adj_weight").alias("est"))

    def errors(self, answers: DataFrame, runs: DataFrame) -> DataFrame:
        """(setting, method, s, abs_error, rel_error, share): means over queries and seeds. runs (method, s, seed) names every
        run, so that a query whose boxes hold no sampled key counts with an answer of zero."""
        every = F.broadcast(runs).join(self.truth, F.lit(True)).join(answers, ["method", "s", "seed", "query_id"], "left")
        off = F.abs(F.coalesce("est", F.lit(0.0)) - F.col("exact"))
        total = F.lit(float(max(1, self.plane.total)))
        return every.groupBy("setting", "method", "s").agg(
            F.avg(off / total).alias("abs_error"), F.avg(F.when(F.col("exact") > 0, off / F.col("exact"))).alias("rel_error"), F.avg(F.col("exact") / total).alias("share")
        )


def _tag(df: DataFrame, method: str, s: int, seed: int) -> DataFrame:
    return df.select("*", F.lit(method).alias("method"), F.lit(s).alias("s"), F.lit(seed).alias("seed"))


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def fitted_digest(p: P.Plane, s: int) -> DataFrame:
    """A 2-d digest of about s nodes and no more: built at the share that allows s, and once more where it makes far fewer."""
    at = lambda share: keep(qdigest.build_2d(p.points, "x", "y", "w", *p.bits, share, p.total))
    first = at(1.0 / max(1, s - 1))
    n = first.count()
    if n >= s / 2:
        return first
    again = at(1.0 / max(1, s - 1) * n / s)
    return again if again.count() <= s else first


def draw(p: P.Plane, s: int, seed: int, method: str = "aware", factor: float | str = 5) -> S.Summary:
    if method == "aware":
        return T.two_pass(p.keys, s, T.Product(["x", "y"]), factor, seed=seed)
    return {"oblivious": S.varopt, "poisson": S.poisson}[method](p.keys, s, seed=seed)


def drawn(p: P.Plane, wanted: list[tuple[str, int, int, float | str]]) -> list[DataFrame]:
    """Points (x, y, adj_weight) of the samples (method, s, seed, factor). A draw rests on these alone, so the plane holds each once."""
    new = [k for k in dict.fromkeys(wanted) if k not in p.drawn]

    def one(k):
        method, s, seed, factor = k
        p.drawn[k] = keep(draw(p, s, seed, method, factor).rows.select("x", "y", "adj_weight"))

    with ThreadPoolExecutor(AT_ONCE if max((k[1] for k in new), default=0) <= SMALL_SAMPLE else 1) as pool:
        list(pool.map(one, new))
    return [p.drawn[k] for k in wanted]


def run(b: Batteries, sizes, methods=("aware", "oblivious"), seeds: int = SEEDS, factors=(5,)) -> DataFrame:
    """Errors of every method at every size on all batteries. With several guide factors, methods are named aware x<factor>."""
    p, asked, answers, runs = b.plane, [], [], []
    coefficients = keep(wavelet.top(p.points, "x", "y", "w", *p.bits, max(sizes))).where("ix >= 0") if "wavelet" in methods else None
    boxes = b.boxes.drop("setting")
    for s in sizes:
        for m in methods:
            if m in ("aware", "oblivious", "poisson"):
                for f in factors if m == "aware" else (5,):
                    name = m if len(factors) == 1 else f"{m} x{f}"
                    asked += [(name, (m, s, seed, f)) for seed in range(1, seeds + 1)]
                continue
            if m == "wavelet":
                got = wavelet.query_all(keep(wavelet.largest(coefficients, s)), boxes, *p.bits)
            elif m == "qdigest":
                got = qdigest.query(fitted_digest(p, s), boxes)
            else:
                got = sketch.query(keep(sketch.build(p.points, "x", "y", "w", *p.bits, s, portable=False, boxes=boxes)), boxes, *p.bits, s, portable=False)
            answers.append(_tag(keep(got.select("query_id", F.col("est").cast("double").alias("est"))), m, s, 0))
            runs.append((m, s, 0))
    if asked:
        runs += [(name, s, seed) for name, (_, s, seed, _) in asked]
        points = [_tag(rows, name, s, seed) for rows, (name, (_, s, seed, _)) in zip(drawn(p, [k for _, k in asked]), asked, strict=True)]
        answers.append(b.answered(keep(_union(points)), "method", "s", "seed"))
    named = p.keys.sparkSession.createDataFrame(runs, "method string, s int, seed int")
    return keep(b.errors(_union([a.select("method", "s", "seed", "query_id", "est") for a in answers]), named))


def area(p: P.Plane, queries: int = QUERIES, rects: int = 25, scale: float = 0.3, seed: int = 1) -> list[tuple]:
    return W.uniform_area(p.wide, p.high, queries, rects, scale, seed)


def _plane(spark, d, which: str | P.Plane) -> P.Plane:
    return which if isinstance(which, P.Plane) else P.plane(spark, d, which)


def error_vs_size(spark, d, which="pairs", sizes=(100, 300, 1000, 3000), methods=ALL, queries=QUERIES, **how) -> DataFrame:
    """Uniform-area queries of 25 ranges. Sizes may be shares of the number of keys."""
    p = _plane(spark, d, which)
    return run(Batteries(p, {"area": area(p, queries)}), [max(1, round(s * p.n)) if s < 1 else s for s in sizes], methods, **how)


def error_vs_area(spark, d, which="events", s=2700, scales=(1.0, 0.3, 0.1, 0.03), methods=("aware", "oblivious", "wavelet", "qdigest"), queries=QUERIES, **how) -> DataFrame:
    p = _plane(spark, d, which)
    return run(Batteries(p, {f"area {x}": area(p, queries, scale=x) for x in scales}), [s], methods, **how)


def error_vs_weight(spark, d, which="pairs", s=2700, levels=(4, 6, 8, 10), methods=("aware", "oblivious", "wavelet", "qdigest"), queries=QUERIES, **how) -> DataFrame:
    """Uniform-weight queries of 10 ranges, each a cell of one level: 10 / 2^level of the weight."""
    p = _plane(spark, d, which)
    return run(Batteries(p, {f"level {n}": P.weight_boxes(P.weight_cells(p, n), n, queries, 10) for n in levels}), [s], methods, **how)


def _level(ranges: int, weight: float) -> int:
    """The level at which so many cells hold about that share of the weight."""
    return max(0, round(math.log2(ranges / weight)))


def error_vs_ranges(spark, d, which="pairs", s=2700, ranges=(1, 2, 5, 10, 20, 40, 80), weight=0.12, methods=("aware", "oblivious", "wavelet"), queries=QUERIES, **how) -> DataFrame:
    """Ever more ranges of together about the same weight."""
    p = _plane(spark, d, which)
    return run(Batteries(p, {f"ranges {r}": P.weight_boxes(P.weight_cells(p, _level(r, weight)), _level(r, weight), queries, r) for r in ranges}), [s], methods, **how)


def guide_sweep(spark, d, which="pairs", s=1000, factors=(1, 2, 5, 10, 20), queries=QUERIES, **how) -> DataFrame:
    p = _plane(spark, d, which)
    return run(Batteries(p, {"area": area(p, queries)}), [s], ("aware",), factors=factors, **how)


def errors_of(rows: DataFrame, column: str = "abs_error") -> dict[tuple[str, str, int], float]:
    return {(r.setting, r.method, r.s): r[column] for r in rows.collect()}


def directions(spark, d) -> list[tuple[str, bool]]:
    """What the experiments are to show: who wins, and how the errors move."""
    p = P.plane(spark, d, "pairs")
    size = errors_of(error_vs_size(spark, d, p, (300, 1000), ("aware", "oblivious", "qdigest", "sketch"), seeds=3))
    ranges = errors_of(error_vs_ranges(spark, d, p, 1000, (1, 40), methods=("aware", "oblivious"), seeds=4))
    weight = error_vs_weight(spark, d, p, 1000, (4, 7), ("aware", "oblivious"), seeds=4)
    absolute, relative = errors_of(weight), errors_of(weight, "rel_error")
    guide = errors_of(guide_sweep(spark, d, p, 300, (1, 5, 20), seeds=4))
    few, many = (ranges[(f"ranges {n}", "aware", 1000)] / ranges[(f"ranges {n}", "oblivious", 1000)] for n in (1, 40))
    return [
        ("aware beats oblivious at both sizes", all(size[("area", "aware", s)] < size[("area", "oblivious", s)] for s in (300, 1000))),
        ("errors fall with the size", all(size[("area", m, 1000)] < size[("area", m, 300)] for m in ("aware", "oblivious"))),
        ("the sketch is the worst", all(size[("area", "sketch", s)] > max(size[("area", m, s)] for m in ("aware", "oblivious", "qdigest")) for s in (300, 1000))),
        ("the gain is largest with few ranges", few < many),
        ("aware beats oblivious on heavy queries", absolute[("level 4", "aware", 1000)] < absolute[("level 4", "oblivious", 1000)]),
        ("relative errors fall with the weight", all(relative[("level 4", m, 1000)] < relative[("level 7", m, 1000)] for m in ("aware", "oblivious"))),
        ("a guide beyond five times the size gains little", guide[("area", "aware x20", 300)] > 0.5 * guide[("area", "aware x5", 300)]),
    ]


def timed(f) -> float:
    t = time.perf_counter()
    f()
    return time.perf_counter() - t


def _full(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def build_times(spark, d, sizes=(100, 1000), which="pairs", methods=("oblivious", "poisson", "aware", *ALL[2:])) -> list[dict]:
    """Seconds and keys a second of every builder at every size; `touched` cells or coefficients of all points one by one,
    `made` before pruning, and the bytes of the summary."""
    p = P.plane(spark, d, which)
    out = []
    for s in sizes:
        for m in methods:
            made = []
            if m in ("oblivious", "poisson", "aware"):
                sec, touched, made = timed(lambda m=m, s=s: _full(draw(p, s, 1, m).rows)), p.n, [s]
            elif m == "wavelet":
                sec = timed(lambda s=s, made=made: made.append(keep(wavelet.top(p.points, "x", "y", "w", *p.bits, s))))
                touched, made = wavelet.contributions(p.n, *p.bits), [made[0].where("ix < 0").first().signed]
            elif m == "qdigest":
                sec = timed(lambda s=s, made=made: made.append(keep(qdigest.build_2d(p.points, "x", "y", "w", *p.bits, 1.0 / s, p.total))))
                touched, made = p.n * (sum(p.bits) + 1), [made[0].count()]
            else:
                sec = timed(lambda s=s, made=made: made.append(keep(sketch.build(p.points, "x", "y", "w", *p.bits, s, portable=False))))
                touched, made = 3 * wavelet.contributions(p.n, *p.bits), [made[0].count()]
            out.append({"method": m, "s": s, "sec": round(sec, 3), "keys_per_sec": round(p.n / sec), "touched": touched, "made": made[0], "bytes": M.size_bytes(min(s, made[0]))})
    return out


def query_times(spark, d, sizes=(100, 1000), which="pairs", queries=100, rects=25) -> list[dict]:
    """Seconds for queries x rects rectangles from each summary, and from the data."""
    p = P.plane(spark, d, which)
    frame = keep(W.frame(spark, area(p, queries, rects, 0.1)))
    out = [{"method": "data", "s": p.n, "sec": round(timed(lambda: _full(P.truth(p, frame))), 3)}]
    coefficients = keep(wavelet.top(p.points, "x", "y", "w", *p.bits, max(sizes))).where("ix >= 0")
    from rangekeep.operators import estimate as E

    for s in sizes:
        for m in ("aware", "oblivious"):
            sm = draw(p, s, 1, m)
            sm = S.Summary(keep(sm.rows), sm.th, sm.seed, sm.structure)
            out.append({"method": m, "s": s, "sec": round(timed(lambda sm=sm: _full(E.estimate_boxes(sm, frame, "x", "y"))), 3)})
        top, nodes = keep(wavelet.largest(coefficients, s)), fitted_digest(p, s)
        cells = keep(sketch.build(p.points, "x", "y", "w", *p.bits, s, portable=False))
        out.append({"method": "wavelet", "s": s, "sec": round(timed(lambda top=top: _full(wavelet.query(top, frame, *p.bits))), 3)})
        out.append({"method": "qdigest", "s": s, "sec": round(timed(lambda nodes=nodes: _full(qdigest.query(nodes, frame))), 3)})
        out.append({"method": "sketch", "s": s, "sec": round(timed(lambda cells=cells, s=s: _full(sketch.query(cells, frame, *p.bits, s, portable=False))), 3)})
    return out
