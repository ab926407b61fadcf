"""kd trees that balance probability mass: built from arrays, located by vectors, with ordered or hierarchical axes.

An axis is a vector (ordered), a `Codes` vector (integer codes whose leading bits are a binary hierarchy) or a matrix of
levels, coarse to fine (a hierarchy of any fan-out).
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


class Codes(np.ndarray):
    """A vector of integer codes that is cut at prefixes only."""

    @staticmethod
    def of(v: np.ndarray) -> Codes:
        return np.asarray(v, np.int64).view(Codes)


@dataclass
class Tree:
    """Nodes in the order of their making; node 0 is the root. Leaves have axis -1."""

    axis: list[int] = field(default_factory=list)
    cut: list = field(default_factory=list)
    left: list[int] = field(default_factory=list)
    right: list[int] = field(default_factory=list)
    parent: list[int] = field(default_factory=list)
    depth: list[int] = field(default_factory=list)
    mass: list[float] = field(default_factory=list)
    #: What locate() reads, made once.
    flat: tuple | None = field(default=None, repr=False, compare=False)

    def __getstate__(self) -> dict:
        """A tree on its way to tasks is arrays, not lists of millions of objects; there it locates points and does no more."""
        return {"flat": self._flat()}

    def _flat(self) -> tuple:
        """(axis, left, right, low, high, cuts of hierarchies by node)."""
        if self.flat is None:
            # an ordered cut is the stretch up to its value, a cut of codes the stretch of one prefix
            low, high, cuts = [-np.inf] * len(self.axis), [0] * len(self.axis), {}
            for i, c in enumerate(self.cut):
                if isinstance(c, tuple) and len(c) == 3:
                    cuts[i] = c
                elif isinstance(c, tuple):
                    low[i], high[i] = c
                elif c is not None:
                    high[i] = c
            self.flat = np.array(self.axis), np.array(self.left), np.array(self.right), np.array(low), np.array(high), cuts
        return self.flat

    def add(self, parent: int, mass: float) -> int:
        self.flat = None
        for a, v in ((self.axis, -1), (self.cut, None), (self.left, -1), (self.right, -1), (self.parent, parent), (self.depth, 0 if parent < 0 else self.depth[parent] + 1), (self.mass, mass)):
            a.append(v)
        return len(self.axis) - 1

    def leaves(self) -> list[int]:
        return [i for i, a in enumerate(self.axis) if a < 0]

    def locate(self, axes: list[np.ndarray]) -> np.ndarray:
        """Leaf of each point; every point of the domain lies in one."""
        at = np.zeros(len(axes[0]), np.int64)
        axis, left, right, low, high, cuts = self._flat()
        while True:
            moving = np.flatnonzero(axis[at] >= 0)
            if not len(moving):
                return at
            node = at[moving]
            go = np.zeros(len(moving), bool)
            for k, values in enumerate(axes):
                mine = axis[node] == k
                if not mine.any():
                    continue
                if values.ndim == 1:
                    v, n = np.asarray(values)[moving[mine]], node[mine]
                    go[mine] = (low[n] <= v) & (v <= high[n])
                    continue
                rows = np.flatnonzero(mine)
                rows = rows[np.argsort(node[rows], kind="stable")]
                for part in np.split(rows, np.flatnonzero(np.diff(node[rows])) + 1):
                    go[part] = goes_left(values[moving[part]], cuts[node[part[0]]])
            at[moving] = np.where(go, left[node], right[node])


def ordered_cut(v: np.ndarray, m: np.ndarray):
    """The value below the largest that splits the mass most evenly, ties to the smaller; None if all values agree."""
    order = np.argsort(v, kind="stable")
    sv, c = v[order], np.cumsum(m[order])
    ends = np.flatnonzero(sv[1:] != sv[:-1])
    if not len(ends):
        return None
    return sv[ends[np.abs(2 * c[ends] - c[-1]).argmin()]]


def _subset(masses: np.ndarray, goal: float) -> np.ndarray:
    """Positions whose masses come nearest the goal, neither none nor all: exact up to 16, else by falling size while it fits."""
    n = len(masses)
    if n <= 16:
        sums = np.zeros(1)
        for m in masses:
            sums = np.concatenate([sums, sums + m])
        best = int(np.abs(sums[1:-1] - goal).argmin()) + 1
        return np.flatnonzero((best >> np.arange(n)) & 1)
    got, held = [], 0.0
    for i in np.lexsort((np.arange(n), -masses)):
        if (abs(held + masses[i] - goal) <= abs(held - goal) and len(got) < n - 1) or not got:
            got.append(i)
            held += masses[i]
    return np.array(sorted(got))


def code_cut(v: np.ndarray, m: np.ndarray):
    """(low, high) of the codes under one prefix whose mass comes nearest half: down the heavier child while it has over half."""
    order = np.argsort(v, kind="stable")
    sv, c = np.asarray(v)[order], np.concatenate([[0.0], np.cumsum(m[order])])
    lo, hi = 0, len(sv)
    while int(sv[lo]) != int(sv[hi - 1]):
        bit = (int(sv[lo]) ^ int(sv[hi - 1])).bit_length() - 1
        at = lo + int(np.searchsorted(sv[lo:hi], (int(sv[hi - 1]) >> bit) << bit))
        lo, hi = (lo, at) if c[at] - c[lo] >= c[hi] - c[at] else (at, hi)
        if 2 * (c[hi] - c[lo]) <= c[-1]:
            break
    # one code may outweigh all others: it stands against them
    if hi - lo == len(sv):
        return None
    apart = int(sv[lo]) ^ int(sv[hi - 1])
    fixed = apart.bit_length()
    # the widest prefix that holds these codes and no other code at hand
    while True:
        start = (int(sv[lo]) >> (fixed + 1)) << (fixed + 1)
        if fixed >= 62 or (lo and int(sv[lo - 1]) >= start) or (hi < len(sv) and int(sv[hi]) < start + (1 << (fixed + 1))):
            break
        fixed += 1
    start = (int(sv[lo]) >> fixed) << fixed
    return start, start + (1 << fixed) - 1


def hierarchical_cut(levels: np.ndarray, m: np.ndarray):
    """(prefix, children that go left, whether the rest of the tree goes left): down the heaviest child while it has over half."""
    total, prefix, inside = m.sum(), (), np.ones(len(m), bool)
    for d in range(levels.shape[1]):
        names, back = np.unique(levels[inside, d], return_inverse=True)
        masses = np.bincount(back, m[inside])
        if len(names) > 1 and (2 * masses.max() <= total or d == levels.shape[1] - 1):
            pick = _subset(masses, total / 2)
            other = total - m[inside].sum()
            side = abs(masses[pick].sum() + other - total / 2) < abs(masses[pick].sum() - total / 2)
            return prefix, frozenset(names[pick].tolist()), bool(side)
        heaviest = names[masses.argmax()]
        below = inside & (levels[:, d] == heaviest)
        if len(names) > 1 and len(np.unique(levels[below][:, d + 1 :], axis=0)) <= 1:
            # one child outweighs the rest and can't be split: it stands against all others
            return prefix, frozenset((heaviest,)), False
        prefix, inside = (*prefix, heaviest), below
    return None


def goes_left(levels: np.ndarray, cut) -> np.ndarray:
    prefix, names, rest_left = cut
    inside = np.ones(len(levels), bool)
    for d, p in enumerate(prefix):
        inside &= levels[:, d] == p
    return np.where(inside, np.isin(levels[:, len(prefix)], np.array(sorted(names))), rest_left)


def build(axes: list[np.ndarray], mass: np.ndarray, leaf_mass: float | None = None, first_axis: int = 0, depth: int | None = None, jitter=None) -> tuple[Tree, np.ndarray]:
    """(tree, leaf of each point). Axes take turns; one whose values agree passes its turn on.

    leaf_mass stops at that much mass, otherwise at single points; depth stops there as well. jitter(node) in (0, 1)
    moves an ordered cut away from the middle.
    """
    tree, leaf = Tree(), np.zeros(len(mass), np.int64)
    todo = [(np.arange(len(mass)), tree.add(-1, float(mass.sum())))]
    while todo:
        rows, node = todo.pop()
        d = tree.depth[node]
        leaf[rows] = node
        if len(rows) < 2 or (leaf_mass is not None and mass[rows].sum() <= leaf_mass) or (depth is not None and d >= depth):
            continue
        for turn in range(len(axes)):
            k = (d + first_axis + turn) % len(axes)
            v = axes[k][rows]
            if isinstance(v, Codes):
                cut = code_cut(v, mass[rows])
                go = (cut[0] <= np.asarray(v)) & (np.asarray(v) <= cut[1]) if cut is not None else None
            elif v.ndim == 1:
                m = mass[rows]
                cut = ordered_cut(v, m) if jitter is None else _off_middle(v, m, jitter(node))
                go = v <= cut if cut is not None else None
            else:
                cut = hierarchical_cut(v, mass[rows])
                go = goes_left(v, cut) if cut is not None else None
            if cut is not None and go.any() and not go.all():
                break
        else:
            continue
        tree.axis[node], tree.cut[node] = k, cut if not isinstance(cut, np.generic) else cut.item()
        tree.left[node] = tree.add(node, float(mass[rows[go]].sum()))
        tree.right[node] = tree.add(node, float(mass[rows[~go]].sum()))
        todo += [(rows[go], tree.left[node]), (rows[~go], tree.right[node])]
    return tree, leaf


def _off_middle(v: np.ndarray, m: np.ndarray, share: float):
    order = np.argsort(v, kind="stable")
    sv, c = v[order], np.cumsum(m[order])
    ends = np.flatnonzero(sv[1:] != sv[:-1])
    return None if not len(ends) else sv[ends[np.abs(c[ends] - share * c[-1]).argmin()]]


def leaf_boxes(tree: Tree, low: list, high: list) -> dict[int, list[tuple]]:
    """Half-open integer boxes of the leaves inside the domain, for ordered axes."""
    out, todo = {}, [(0, list(zip(low, high, strict=True)))]
    while todo:
        node, box = todo.pop()
        if tree.axis[node] < 0:
            out[node] = box
            continue
        k, c = tree.axis[node], tree.cut[node]
        todo.append((tree.left[node], [(a, min(b, c + 1)) if i == k else (a, b) for i, (a, b) in enumerate(box)]))
        todo.append((tree.right[node], [(max(a, c + 1), b) if i == k else (a, b) for i, (a, b) in enumerate(box)]))
    return out
