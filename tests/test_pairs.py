"""The pair step and the chain against every outcome, in exact arithmetic."""

import itertools
from fractions import Fraction as Fr

import numpy as np
import pytest

from rangekeep.functions import UNIT
from rangekeep.operators import local


def outcomes(p):
    """All end states of the left-to-right chain with their probabilities."""
    states = {(tuple(p), 0): Fr(1)}
    done = {}
    while states:
        (p, k), w = states.popitem()
        open_ = [i for i in range(len(p)) if 0 < p[i] < 1]
        if len(open_) < 2:
            done[p] = done.get(p, 0) + w
            continue
        i, j = open_[0], open_[1]
        total = p[i] + p[j]
        if total < 1:
            ways = [((total, Fr(0)), p[i] / total), ((Fr(0), total), p[j] / total)]
        else:
            ways = [((Fr(1), total - 1), (1 - p[j]) / (2 - total)), ((total - 1, Fr(1)), (1 - p[i]) / (2 - total))]
        for (a, b), odds in ways:
            if odds:
                q = list(p)
                q[i], q[j] = a, b
                states[(tuple(q), k + 1)] = states.get((tuple(q), k + 1), 0) + w * odds
    return done


@pytest.mark.parametrize("p", [["3/10", "6/10", "4/10", "7/10"], ["1/2"] * 4, ["9/10", "1/10", "5/10", "5/10"], ["1/12", "5/12", "6/12", "11/12", "1/12"]])
def test_expectation_and_bounds(p):
    p = [Fr(x) for x in p]
    ends = outcomes(p)
    assert sum(ends.values()) == 1
    for i in range(len(p)):
        assert sum(w * e[i] for e, w in ends.items()) == p[i]
    for n in range(1, len(p) + 1):
        for js in itertools.combinations(range(len(p)), n):
            inside, outside, joint, none = Fr(1), Fr(1), Fr(0), Fr(0)
            for j in js:
                inside, outside = inside * p[j], outside * (1 - p[j])
            for e, w in ends.items():
                a, b = Fr(1), Fr(1)
                for j in js:
                    a, b = a * e[j], b * (1 - e[j])
                joint, none = joint + w * a, none + w * b
            assert joint <= inside and none <= outside
    for e in ends:
        assert sum(e) == sum(p)


def test_pair_step_hits_both_ends():
    assert local.pair_step(3, 4, 0.0, 10) == (7, 0) and local.pair_step(3, 4, 0.99, 10) == (0, 7)
    assert local.pair_step(6, 7, 0.0, 10) == (10, 3) and local.pair_step(6, 7, 0.99, 10) == (3, 10)
    assert sorted(local.pair_step(9, 1, 0.5, 10)) == [0, 10]


def test_chain_means():
    p = np.array([0.3, 0.6, 0.4, 0.7, 0.1, 0.8, 0.4, 0.2, 0.3, 0.2])
    t = np.floor(p * UNIT + 0.5).astype(np.int64)
    rng, runs, hits = np.random.default_rng(5), 20_000, np.zeros(10)
    group, u = np.repeat(np.arange(runs), 10), rng.random(runs * 10)
    for lo in range(0, runs, 2000):
        part = slice(lo * 10, (lo + 2000) * 10)
        got, left, mass = local.chain(group[part], np.tile(t, 2000), u[part])
        hits += np.bincount(got % 10, minlength=10)
        hits += np.bincount(left[mass * 2 >= UNIT] % 10, minlength=10)
    z = (hits / runs - p) / np.sqrt(p * (1 - p) / runs)
    assert np.abs(z).max() < 4.5 and abs(hits.sum() - 4 * runs) <= runs * 0.001


def test_ten_leaf_example():
    """The worked example replayed pair by pair, nearest relatives first: it ends in leaves 2, 3, 7, 10, and every node holds floor or ceiling."""
    p = [Fr(x, 10) for x in (3, 6, 4, 7, 1, 8, 4, 2, 3, 2)]
    leaf = lambda *at: [(i - 1, j - 1, who) for i, j, who in at]
    # who of a pair becomes decided: a sum under one settles one at zero, a sum from one on settles one at one
    rounds = leaf((1, 2, "first"), (3, 4, "first"), (6, 7, "second"), (8, 9, "second"), (2, 4, "first"), (8, 10, "first"), (6, 10, "first"), (5, 10, "second"))
    states = local.replay(p, rounds)
    # each step keeps the sum, decides one of its two keys at least, and is an outcome that the pair step has
    before = p
    for (i, j, _), after in zip(rounds, states, strict=True):
        assert sum(after) == 4 and {after[i], after[j]} & {0, 1} and after[i] + after[j] == before[i] + before[j]
        outcomes_of = {local.pair_step(before[i], before[j], u) for u in (0, Fr(999_999, 1_000_000))}
        assert (after[i], after[j]) in outcomes_of
        before = after
    assert {i + 1 for i, x in enumerate(states[-1]) if x == 1} == {2, 3, 7, 10} and set(states[-1]) == {0, 1}
    # the masses printed after the first four steps, the next two and the last two
    printed = {3: (0, 9, 10, 1, 1, 2, 10, 5, 0, 2), 5: (0, 10, 10, 0, 1, 2, 10, 0, 0, 7), 6: (0, 10, 10, 0, 1, 0, 10, 0, 0, 9), 7: (0, 10, 10, 0, 0, 0, 10, 0, 0, 10)}
    assert all(states[k] == [Fr(x, 10) for x in row] for k, row in printed.items())
    nodes = [{1, 2}, {3, 4}, {1, 2, 3, 4}, {6, 7}, {8, 9}, {8, 9, 10}, {6, 7, 8, 9, 10}, {5, 6, 7, 8, 9, 10}, set(range(1, 11))]
    for n in nodes:
        mass = sum(p[i - 1] for i in n)
        assert mass.__floor__() <= len({2, 3, 7, 10} & n) <= mass.__ceil__()


def test_general_loop_keeps_sum():
    import random

    p = local.aggregate([3, 6, 4, 7, 1, 8, 4, 2, 3, 2], unit=10, rng=random.Random(3))
    assert sum(p) == 40 and set(p) <= {0, 10}
    states = local.replay([3, 6, 4, 7], [(0, 1, "first"), (2, 3, "second")], unit=10)
    assert states[0][:2] == [0, 9] and states[1][2:] == [1, 10]


def test_shrink_keeps_total():
    w = np.random.default_rng(1).pareto(1.2, 500) * 100 + 1
    rows, adj = local.shrink(w, 50, np.random.default_rng(2).integers(0, 1 << 62, 500), 0)
    assert len(rows) == len(set(rows)) == 50 and abs(adj.sum() / w.sum() - 1) < 1e-9


def test_checks_of_replicates():
    """The loop passes the checks of an aggregation; one shared offset for all draws does not."""
    import random

    from rangekeep.operators.metrics import check_aggregate

    p, rng = [5] * 6, random.Random(1)
    runs = np.array([local.aggregate(p, unit=10, rng=rng) for _ in range(4000)]) / 10
    pairs = [[i, j] for i in range(6) for j in range(i)]
    assert all(check_aggregate(runs, np.full(6, 0.5), pairs).values())
    shared = np.array([[1, 0] * 3 if rng.random() < 0.5 else [0, 1] * 3 for _ in range(4000)])
    assert not check_aggregate(shared, np.full(6, 0.5), pairs)["inclusion"]
