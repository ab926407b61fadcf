"""Two read-only passes with memory for the sample and its cells, whatever the data's size.

Pass one is a single job: a bounded reservoir draws a guide sample larger than the wanted one and adds up the keys'
weight and number, from which the threshold follows, since the guide holds every key that is heavy for the smaller
sample. The guide's light keys cut the domain into cells. Pass two emits heavy keys at once and chains the light keys
of each cell as they come, task by task; a task keeps one undecided key a cell. What the tasks leave undecided meets
per cell, and the cells' last keys settle by the structure on the driver: at most one row for each cell, and cells are
as many as the guide has keys, or their ancestors.

Every draw is a number made from the key's hash and the step it is for; the order in which keys meet has nothing to do
with their draws.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangekeep.functions import UNIT, uniform
from rangekeep.operators import kdtree, local
from rangekeep.operators.ipps import Threshold, threshold, totals, with_inclusion
from rangekeep.operators.structures import Summary, reservoir
from rangekeep.sources.shared import keep
from rangekeep.streaming.reservoir import gathered, varopt_reservoir


def _values(column) -> np.ndarray:
    """A column as an array that can be sorted: times as whole numbers, nulls before all else."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if pa.types.is_temporal(column.type):
        column = column.cast(pa.timestamp("us") if pa.types.is_timestamp(column.type) else pa.int32()).cast(pa.int64())
    if column.null_count:
        least = "" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else float("-inf") if pa.types.is_floating(column.type) else -(1 << 62)
        column = column.fill_null(pa.scalar(least, column.type if least != -(1 << 62) else pa.int64()).cast(column.type))
    return np.asarray(column.to_numpy(zero_copy_only=False))


class _Ranks:
    """Numbers for the values of a column that a guide has met: 2i + 1 for the i-th, even numbers for the gaps between."""

    def __init__(self, met: np.ndarray):
        self.met = np.unique(met)

    def __call__(self, values: np.ndarray) -> np.ndarray:
        if values.dtype == object:
            some, back = np.unique(values, return_inverse=True)
            return self._of(some)[back]
        return self._of(values)

    def _of(self, values):
        return (np.searchsorted(self.met, values, "left") + np.searchsorted(self.met, values, "right")).astype(np.int64)


@dataclass(frozen=True)
class Prefixes:
    """An axis of whole, non-negative codes whose leading bits are a binary hierarchy."""

    column: str

    @property
    def columns(self) -> list[str]:
        return [self.column]


@dataclass(frozen=True)
class Levels:
    """An axis that is a hierarchy of any fan-out: columns from coarse to fine, null below a short path's end."""

    path: tuple[str, ...]

    @property
    def columns(self) -> list[str]:
        return list(self.path)


class _Names:
    """Whole numbers for the values of each level of a hierarchical axis; -1 for values that the guide has not met."""

    def __init__(self, cols: list[np.ndarray]):
        self.ranks = [_Ranks(c) for c in cols]

    def __call__(self, cols: list[np.ndarray]) -> np.ndarray:
        each = [r(c) for r, c in zip(self.ranks, cols, strict=True)]
        return np.stack([np.where(e % 2 == 1, e // 2, -1) for e in each], axis=1)


@dataclass
class Product:
    """Cells are the leaves of a kd tree over the guide; axes are column names (ordered), Prefixes or Levels."""

    axes: list
    leaf_mass: float | None = None
    first_axis: int = 0

    @property
    def columns(self) -> list[str]:
        return [c for a in self.axes for c in ([a] if isinstance(a, str) else a.columns)]

    def _arrays(self, cols: list[np.ndarray]) -> list[np.ndarray]:
        out, at = [], iter(cols)
        for i, a in enumerate(self.axes):
            if isinstance(a, str):
                out.append(next(at))
            elif isinstance(a, Prefixes):
                out.append(kdtree.Codes.of(next(at)))
            else:
                out.append(self.names[i]([next(at) for _ in a.columns]))
        return out

    def grow(self, cols: list[np.ndarray], mass: np.ndarray, depth: int | None = None) -> tuple[kdtree.Tree, np.ndarray]:
        """(tree over these points, leaf of each)."""
        at = iter(cols)
        held = [[next(at) for _ in ([a] if isinstance(a, str) else a.columns)] for a in self.axes]
        self.names = {i: _Names(held[i]) for i, a in enumerate(self.axes) if isinstance(a, Levels)}
        return kdtree.build(self._arrays(cols), mass, self.leaf_mass, self.first_axis, depth)

    def fit(self, cols: list[np.ndarray], mass: np.ndarray) -> Product:
        self.tree, _ = self.grow(cols, mass)
        return self

    def locate(self, cols: list[np.ndarray]) -> np.ndarray:
        return self.tree.locate(self._arrays(cols))

    def finish(self, cell, ticks, draw) -> np.ndarray:
        return local.settle_tree(cell, ticks, np.array(self.tree.parent), np.array(self.tree.depth), draw)

    def up(self) -> np.ndarray | None:
        return np.array(self.tree.parent)


class _Sequence:
    """Cells along a line: what is left of them settles from one end to the other."""

    def finish(self, cell, ticks, draw):
        order = np.argsort(cell, kind="stable")
        got, left, mass = local.chain(np.zeros(len(order), np.int64), ticks[order], draw(0, order))
        out = order[got]
        return np.append(out, order[left[:1]]) if len(left) and mass[0] * 2 >= UNIT else out

    def up(self) -> np.ndarray | None:
        """The parents of nodes of a tree; None where cells are a line."""
        return None


@dataclass
class Order(_Sequence):
    """Cells are the stretches between guide keys, each closed at its right end, and both tails."""

    column: str

    @property
    def columns(self) -> list[str]:
        return [self.column]

    def fit(self, cols, mass) -> Order:
        self.cuts = np.unique(cols[0])
        return self

    def locate(self, cols):
        return np.searchsorted(self.cuts, cols[0], side="left").astype(np.int64)


@dataclass
class Disjoint(_Sequence):
    """A cell for each range that the guide has met and one for each gap between such ranges in a fixed order."""

    column: str

    @property
    def columns(self) -> list[str]:
        return [self.column]

    def fit(self, cols, mass) -> Disjoint:
        self.ranks = _Ranks(cols[0])
        return self

    def locate(self, cols):
        return self.ranks(cols[0])


@dataclass
class Hierarchy(_Sequence):
    """path: columns from coarse to fine. mode "linear" takes them as one order; "ancestors" makes a cell of every ancestor of a guide key.

    Nodes are found level by level from (node above, number of the value), as whole numbers.
    """

    path: list[str]
    mode: str = "ancestors"
    steps: list = field(default_factory=list, repr=False)

    @property
    def columns(self) -> list[str]:
        return self.path

    def fit(self, cols, mass) -> Hierarchy:
        self.steps, at = [], np.zeros(len(cols[0]), np.int64)
        parent, depth, first = [np.array([-1])], [np.array([0])], 1
        for d, c in enumerate(cols, 1):
            ranks = _Ranks(c)
            many = 2 * len(ranks.met) + 1
            known = np.unique(at * many + ranks(c))
            self.steps.append((ranks, many, known, first))
            if self.mode == "linear":
                at = 2 * np.searchsorted(known, at * many + ranks(c)) + 1
            else:
                at = first + np.searchsorted(known, at * many + ranks(c))
                parent.append(known // many)
                depth.append(np.full(len(known), d))
                first += len(known)
        self.parent, self.depth = np.concatenate(parent), np.concatenate(depth)
        return self

    def locate(self, cols):
        at = np.zeros(len(cols[0]), np.int64)
        if self.mode == "linear":
            # guide rows before a key: prefixes that the guide has met are odd, what lies between them even
            for c, (ranks, many, known, _) in zip(cols, self.steps, strict=True):
                code = at * many + ranks(c)
                left = np.searchsorted(known, code, "left")
                at = left + np.searchsorted(known, code, "right")
            return (at // 2).astype(np.int64)
        alive = np.ones(len(at), bool)
        for c, (ranks, many, known, first) in zip(cols, self.steps, strict=True):
            if not len(known):
                break
            code = at * many + ranks(c)
            place = np.minimum(np.searchsorted(known, code), len(known) - 1)
            alive &= known[place] == code
            at = np.where(alive, first + place, at)
        return at

    def finish(self, cell, ticks, draw):
        return super().finish(cell, ticks, draw) if self.mode == "linear" else local.settle_tree(cell, ticks, self.parent, self.depth, draw)

    def up(self):
        return None if self.mode == "linear" else self.parent


@dataclass
class Guide:
    """Rows of a guide sample, what each stands for, and the totals of all keys."""

    rows: pa.Table
    stands: np.ndarray
    total: int
    n: int
    th: Threshold | None = None


def _arrow(rows: DataFrame) -> pa.Table:
    return rows.orderBy("hk").toArrow()


def draw_guide(keys: DataFrame, size: int, kind: str = "varopt", columns: list[str] | None = None, seed: int = 1, s: int | None = None) -> Guide:
    """A guide of about size keys. "varopt": one scan, with the totals. "poisson": independent draws at the threshold of
    that size, which takes scans of its own. "reservoir": all keys equally likely, for about uniform weights; it may miss
    heavy keys, so the threshold for s is then found by itself."""
    cols = list(dict.fromkeys(["hk", "units", *(columns or [])]))
    if kind == "varopt":
        t = _arrow(varopt_reservoir(keys, size, seed, columns=tuple(cols), totals=True))
        whole = [int(np.asarray(t.column(c)).sum()) if t.num_rows else 0 for c in ("hi", "lo", "met")]
        return Guide(t.select(cols), np.asarray(t.column("adj_weight"), np.float64), (whole[0] << 40) + whole[1], whole[2])
    if kind == "poisson":
        th = threshold(keys, size)
        inc = with_inclusion(keys, th.tau)
        t = _arrow(inc.where(F.col("is_heavy") | (uniform("guide", seed, "hk") < F.col("p"))).select(*cols))
        return Guide(t, np.maximum(np.asarray(t.column("units"), np.float64), th.tau), th.total, th.n)
    if kind == "reservoir":
        t = _arrow(reservoir(keys.where("units > 0"), size, "guide", seed).select(*cols))
        w, n = totals(keys)
        return Guide(t, np.asarray(t.column("units"), np.float64) * max(1.0, n / max(1, t.num_rows)), w, n, threshold(keys, s) if s else None)
    raise ValueError(kind)


def threshold_from_guide(guide_units: np.ndarray, total: int, n: int, s: int) -> Threshold:
    """tau from a guide that holds every key heavy at its own, larger size."""
    if n <= s:
        return Threshold(0.0, n, total, total, n, s)
    # whole numbers: products and sums pass 2^53, and 2^63 too
    k, heavy = 0, 0
    for x in np.sort(np.asarray(guide_units, np.int64))[::-1][: s - 1].tolist():
        if x * (s - k) < total - heavy:
            break
        k, heavy = k + 1, heavy + x
    return Threshold((total - heavy) / (s - k), k, heavy, total, n, s)


def _settled(t: pa.Table, ticks: np.ndarray, cell: np.ndarray, held: int, draw: np.ndarray):
    """(table of settled rows, table of undecided rows, their masses and cells); the first `held` rows open their cells."""
    order = np.lexsort((np.arange(len(ticks)) >= held, cell))
    got, left, mass = local.chain(cell[order], ticks[order], draw[order])
    done, last = order[got], order[left]
    return t.take(pa.array(done)), t.take(pa.array(last)), mass, cell[last]


def _cell_pass(structure, turn: int):
    """Rows of keys with hash h and ticks -> settled rows (ticks of a unit) as they come, and one undecided row a cell at the end.

    A row with a unit of ticks is heavy and passes. With structure None, rows bring their cells along.
    """

    def run(batches):
        held, held_t, held_c = None, np.zeros(0, np.int64), np.zeros(0, np.int64)

        def out(t: pa.Table, ticks: np.ndarray, cell: np.ndarray):
            t = t.set_column(t.schema.get_field_index("ticks"), "ticks", pa.array(ticks.astype(np.int64)))
            t = t.set_column(t.schema.get_field_index("cell"), "cell", pa.array(cell.astype(np.int64)))
            yield from t.combine_chunks().to_batches()

        for t in gathered(batches):
            ticks = np.asarray(t.column("ticks"))
            sure = ticks >= UNIT
            if sure.any():
                yield from out(t.filter(pa.array(sure)), ticks[sure], np.full(int(sure.sum()), -1))
                t, ticks = t.filter(pa.array(~sure)), ticks[~sure]
            if not t.num_rows:
                continue
            cell = np.asarray(t.column("cell")) if structure is None else structure.locate([_values(t.column(c)) for c in structure.columns])
            u = local.fresh(np.asarray(t.column("h")), turn)
            n = 0 if held is None else held.num_rows
            if n:
                t, u = pa.concat_tables([held, t]), np.concatenate([np.zeros(n), u])
                ticks, cell = np.concatenate([held_t, ticks]), np.concatenate([held_c, cell])
            done, held, held_t, held_c = _settled(t, ticks, cell, n, u)
            held = held.combine_chunks()
            if done.num_rows:
                yield from out(done, np.full(done.num_rows, UNIT), np.zeros(done.num_rows))
        if held is not None and held.num_rows:
            yield from out(held, held_t, held_c)

    return run


def two_pass(keys: DataFrame, s: int, structure, guide_factor: float | str = 5, guide: str = "varopt", seed: int = 1, stage: str = "two") -> Summary:
    """A sample of size s whose counts follow the structure, from two reads of keys with the default guide.

    keys must not change between the passes; where they take work to make, keep() them first. guide_factor "slogs"
    takes s log s guide keys, as the guarantees ask. Columns named h, cell or ticks are replaced.
    """
    return _two_pass(keys, s, structure, guide_factor, guide, seed, stage)[0]


def _two_pass(keys: DataFrame, s: int, structure, guide_factor: float | str = 5, guide: str = "varopt", seed: int = 1, stage: str = "two") -> tuple[Summary, object]:
    """two_pass() with the fitted structure."""
    if s < 1:
        raise ValueError("s is at least 1")
    size = max(s, int(s * max(1.0, np.log(s))) if guide_factor == "slogs" else int(s * guide_factor))
    g = draw_guide(keys, size, guide, structure.columns, seed, s)
    th = g.th or threshold_from_guide(np.asarray(g.rows.column("units")), g.total, g.n, s)
    name = type(structure).__name__.lower()
    inc = with_inclusion(keys, th.tau)
    weigh = lambda rows: rows.withColumn("adj_weight", F.greatest(F.col("units").cast("double"), F.lit(th.tau)))
    if th.n <= s:
        return Summary(weigh(inc).drop("ticks"), th, seed, name), structure
    light = np.asarray(g.rows.column("units")) < th.tau
    t = g.rows.filter(pa.array(light))
    structure = structure.fit([_values(t.column(c)) for c in structure.columns], g.stands[light] / th.tau)
    rows = inc.where("ticks > 0").withColumn("h", F.xxhash64(F.lit(f"{stage}|{seed}"), "hk")).withColumn("cell", F.lit(0).cast("bigint"))
    passed = keep(rows.mapInArrow(_cell_pass(structure, 0), rows.schema))
    open_ = passed.where(F.col("ticks") < UNIT).repartition("cell").sortWithinPartitions("cell", "hk")
    merged = keep(open_.mapInArrow(_cell_pass(None, 1), rows.schema))
    rest = merged.where(F.col("ticks") < UNIT).select("hk", "h", "cell", "ticks").orderBy("cell", "hk").toArrow()
    cell, ticks, h = (np.asarray(rest.column(c)) for c in ("cell", "ticks", "h"))
    more = structure.finish(cell, ticks, lambda level, r: local.fresh(h[r], 2 + level)) if rest.num_rows else []
    last = keys.sparkSession.createDataFrame(pa.table({"hk": rest.column("hk").take(pa.array(np.asarray(more, np.int64)))}).cast(pa.schema([("hk", pa.string())])))
    # no more rows than the sample has
    chosen = merged.where(F.col("ticks") < UNIT).join(F.broadcast(last) if s <= 1_000_000 else last, "hk", "left_semi").select(rows.columns)
    every = passed.where(F.col("ticks") == UNIT).unionByName(merged.where(F.col("ticks") == UNIT)).unionByName(chosen)
    return Summary(weigh(every.drop("h", "cell", "ticks")), th, seed, name), structure


def _located(structure):
    def run(batches):
        for t in gathered(batches):
            cell = structure.locate([_values(t.column(c)) for c in structure.columns])
            yield pa.RecordBatch.from_arrays([pa.array(cell), t.column("ticks").combine_chunks(), t.column("in").combine_chunks()], ["cell", "ticks", "in"])

    return run


def cell_counts(keys: DataFrame, out: Summary, structure) -> DataFrame:
    """(cell, mass in ticks, n_sampled) of the light keys by the cells of a fitted structure."""
    inc = with_inclusion(keys, out.th.tau).where(~F.col("is_heavy") & (F.col("ticks") > 0))
    chosen = out.rows.where(~F.col("is_heavy")).select("hk", F.lit(1).alias("in"))
    rows = inc.join(F.broadcast(chosen) if out.th.s <= 1_000_000 else chosen, "hk", "left")
    rows = rows.select(*dict.fromkeys(structure.columns), "ticks", F.coalesce("in", F.lit(0)).cast("bigint").alias("in"))
    at = rows.mapInArrow(_located(structure), "cell long, ticks long, in long")
    return at.groupBy("cell").agg(F.sum(F.col("ticks").cast("decimal(38,0)")).alias("mass"), F.sum("in").alias("n_sampled"))


def nodes_off(keys: DataFrame, out: Summary, structure) -> tuple[int, float]:
    """(nodes whose count of sampled keys differs from their mass by one or more, the largest difference).

    Nodes are those of the tree over the cells; where cells are a line, its prefixes. Rounding to ticks moves a mass by half a
    tick a key, which is allowed for. One row a cell reaches the driver, as in the last step of the sampling.
    """
    rows = cell_counts(keys, out, structure).collect()
    if not rows:  # every key is in the sample, or there is none
        return 0, 0.0
    up = structure.up()
    if up is None:
        rows.sort(key=lambda r: r.cell)
        mass, n = [int(r.mass) for r in rows], [r.n_sampled for r in rows]
        off = np.abs(np.cumsum(n) * float(UNIT) - np.cumsum(np.array(mass, np.float64))) / UNIT
    else:
        mass, n = np.zeros(len(up)), np.zeros(len(up))
        for r in rows:
            mass[r.cell], n[r.cell] = float(r.mass), r.n_sampled
        for i in range(len(up) - 1, 0, -1):  # parents come before their children
            mass[up[i]] += mass[i]
            n[up[i]] += n[i]
        off = np.abs(n - mass / UNIT)
    return int((off >= 1.000001).sum()), float(off.max(initial=0.0))
