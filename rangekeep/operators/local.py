"""NumPy twins of the chain, for batches on executors and for the few rows that reach the driver; and the textbook loop for tests."""

from __future__ import annotations

import random

import numpy as np

from rangekeep.functions import UNIT
from rangekeep.operators.ipps import local_threshold


def fresh(h: np.ndarray, turn: int) -> np.ndarray:
    """Numbers in [0, 1) from 64-bit hashes of keys; every turn gives others, apart from each other and from the hashes' order."""
    with np.errstate(over="ignore"):
        x = np.asarray(h).view(np.uint64) + np.uint64((turn + 1) * 0x9E3779B97F4A7C15 % (1 << 64))
        for _ in range(2):
            x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            x = x ^ (x >> np.uint64(31))
    return (x >> np.uint64(11)).astype(np.float64) / float(1 << 53)


def chain(group: np.ndarray, t: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of rows sorted by group: (sampled row numbers, last takers' row numbers, their masses), undecided masses of zero left out."""
    n = len(t)
    if not n:
        e = np.zeros(0, np.int64)
        return e, e, e
    i = np.arange(n)
    first = np.concatenate([[True], group[1:] != group[:-1]])
    c = np.cumsum(t)
    base = np.maximum.accumulate(np.where(first, i, 0))
    inside = c - (c - t)[base]
    q = (inside - t) % UNIT
    total = q + t
    took = first | (u < np.where(total >= UNIT, (UNIT - t) / (2.0 * UNIT - total), t / np.maximum(total, 1)))
    taker = np.maximum.accumulate(np.where(took, i, 0))
    full = np.flatnonzero(total >= UNIT)
    before = taker[np.maximum(full - 1, 0)]
    sampled = np.where(took[full] & ~first[full], before, full)
    end = np.flatnonzero(np.concatenate([first[1:], [True]]))
    mass = inside[end] % UNIT
    return sampled, taker[end][mass > 0], mass[mass > 0]


def settle_tree(node: np.ndarray, t: np.ndarray, parent: np.ndarray, depth: np.ndarray, draw, rest: bool = False):
    """Row numbers sampled when undecided rows at nodes of a tree settle with their nearest relatives first.

    draw(level, rows) gives a uniform number for each row at each level. With rest, (sampled, rows still undecided at
    the root, their masses), and the last row isn't rounded.
    """
    rows, at, mass, out = np.arange(len(t)), node.astype(np.int64), t.astype(np.int64), []
    for level in range(int(depth[at].max(initial=0)), -1, -1):
        here = depth[at] >= level
        order = np.lexsort((rows, np.where(here, at, -1 - np.arange(len(at)))))
        rows, at, mass = rows[order], at[order], mass[order]
        group = np.where(depth[at] >= level, at, -1 - np.arange(len(at)))
        got, left, left_mass = chain(group, mass, draw(level, rows))
        out.append(rows[got])
        rows, at, mass = rows[left], at[left], left_mass
        up = depth[at] >= level
        at = np.where(up & (parent[at] >= 0), parent[at], at)
    if rest:
        return np.concatenate(out), rows, mass
    if len(rows) and mass[0] * 2 >= UNIT:
        out.append(rows[:1])
    return np.concatenate(out) if out else np.zeros(0, np.int64)


def pair_step(a, b, u, unit=1):
    """Two undecided masses become one decided and one undecided, or both decided; every expectation stays.

    Below a unit together, one takes all; from a unit on, one becomes sampled and the other keeps what is over.
    """
    total = a + b
    if total < unit:
        return (total, 0) if u * total < a else (0, total)
    return (unit, total - unit) if u * (2 * unit - total) < unit - b else (total - unit, unit)


def aggregate(masses: list, selector=None, unit=1, rng: random.Random | None = None) -> list:
    """The general loop: any two undecided entries, as selector(undecided positions) names them, until at most one is left."""
    rng, p = rng or random.Random(0), list(masses)
    while True:
        open_ = [i for i, x in enumerate(p) if 0 < x < unit]
        if len(open_) < 2:
            return p
        i, j = selector(open_) if selector else (open_[0], open_[1])
        p[i], p[j] = pair_step(p[i], p[j], rng.random(), unit)


def replay(masses: list, rounds: list[tuple[int, int, str]], unit=1) -> list[list]:
    """States of a scripted run: each round names two positions and which of them is decided, "first" or "second"."""
    p, states = list(masses), []
    for i, j, who in rounds:
        total = p[i] + p[j]
        low, high = (0, total) if total < unit else (unit, total - unit)
        p[i], p[j] = (low, high) if who == "first" else (high, low)
        states.append(list(p))
    return states


def shrink(adjusted: np.ndarray, s: int, h: np.ndarray, turn: int) -> tuple[np.ndarray, np.ndarray]:
    """(kept row numbers, their adjusted weights): s of the rows, blind to structure; all rows if they are no more than s.

    h are 64-bit hashes of the keys; a key must not meet the same turn twice.
    """
    n = len(adjusted)
    if n <= s:
        return np.arange(n), adjusted
    tau = local_threshold(adjusted, float(adjusted.sum()), s)
    t = np.floor(np.minimum(1.0, adjusted / tau) * UNIT + 0.5).astype(np.int64)
    heavy, light = np.flatnonzero(t >= UNIT), np.flatnonzero((t > 0) & (t < UNIT))
    # the order and the draws come from different numbers, or rows late in the order would draw high
    light = light[np.argsort(fresh(h[light], 2 * turn), kind="stable")]
    got, left, mass = chain(np.zeros(len(light), np.int64), t[light], fresh(h[light], 2 * turn + 1))
    rows = np.concatenate([heavy, light[got], light[left[:1]] if len(left) and mass[0] * 2 >= UNIT else light[:0]])
    return rows, np.maximum(adjusted[rows], tau)
