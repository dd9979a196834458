"""Sampling laws against enumerated probabilities, with fixed seeds."""

import itertools
import math

import numpy as np
import pytest

from weightdraw.functions.variates import binomial_inverse, py_uniform
from weightdraw.operators import classes as C
from weightdraw.operators import items as I
from weightdraw.operators.tables import overlay
from weightdraw.streaming.reservoir import jump_batch, reservoir_jumps, reservoir_sequential

W = [1, 2, 3, 4, 5]


def ordered_law(weights, k):
    law = {}
    for perm in itertools.permutations(range(len(weights)), k):
        left, p = sum(weights), 1.0
        for i in perm:
            p *= weights[i] / left
            left -= weights[i]
        law[perm] = p
    return law


def chi_square(counts, law, n):
    return sum((counts.get(x, 0) - n * p) ** 2 / (n * p) for x, p in law.items())


@pytest.mark.parametrize(("cutoff", "gapless"), [(128, False), (0, False), (128, True)])
def test_class_sampler(cutoff, gapless):
    w = np.array([4.0, 5, 6, 7, 7.9])
    rng = np.random.default_rng(5)
    total = np.zeros(5)
    for _ in range(400):
        at, times, _ = C.sample_weights(w, 30, rng, cutoff, True, gapless)
        assert times.sum() == 30
        np.add.at(total, at, times)
    want = w / w.sum() * total.sum()
    assert ((total - want) ** 2 / want).sum() < 20


def test_nodes_follow_distinct_results():
    w = np.ones(100_000)
    rng = np.random.default_rng(1)
    for m in (10, 1000):
        _, times, visited = C.sample_weights(w, m, rng)
        assert visited <= 4 * len(times) * (1 + math.log2(100_000 / len(times)))


def test_clocks_follow_the_ordered_law():
    law, counts, n = ordered_law(W, 2), {}, 3000
    for seed in range(n):
        key = sorted((-math.log(py_uniform(seed, str(i))) / w, i) for i, w in enumerate(W))
        pair = key[0][1], key[1][1]
        counts[pair] = counts.get(pair, 0) + 1
    assert chi_square(counts, law, n) < 45


def test_jumps_follow_the_law_of_the_pair():
    law, counts, n = {}, {}, 3000
    for pair, p in ordered_law(W, 2).items():
        law[frozenset(pair)] = law.get(frozenset(pair), 0) + p
    batches = [[(0, 1), (1, 2)], [(2, 3), (3, 4)], [(4, 5)]]
    for seed in range(n):
        got = frozenset(i for _, i in reservoir_jumps(batches, 2, seed))
        counts[got] = counts.get(got, 0) + 1
    assert chi_square(counts, law, n) < 34


def test_jump_keys_stay_below_the_threshold():
    at, keys = jump_batch(np.full(2000, 2.0), 0.05, np.random.default_rng(2))
    assert len(at) > 50 and (keys < 0.05).all() and (np.diff(at) > 0).all()


def test_sequential_reservoir_equals_smallest_clocks():
    stream = [(i, 1 + i % 7, py_uniform(3, str(i))) for i in range(300)]
    want = [i for _, i in sorted((-math.log(u) / w, i) for i, w, u in stream)[:10]]
    assert reservoir_sequential(stream, 10) == want


def test_binomial_inverse_and_counts():
    assert binomial_inverse(10, 0.0, 0.5) == 0 and binomial_inverse(10, 1.0, 0.5) == 10
    assert sum(C.split_counts([5, 0, 3, 9, 1], 1000, 7)) == 1000
    assert C.split_counts([5, 0, 3, 9, 1], 1000, 7)[1] == 0
    for replace in (True, False):
        got = C.uniform_counts(100, 40, 7, 1, replace)
        assert sum(got) == 40 and (replace or all(x <= 15 for x in got))


def test_overlay_keeps_amounts():
    free, mass = [(0, 5), (1, 0), (2, 7)], [(9, 4), (8, 8)]
    got = overlay(free, mass)
    assert sum(x for *_, x in got) == 12
    assert sum(x for f, _, x in got if f == 0) == 5 and sum(x for _, m, x in got if m == 8) == 8


def test_without_replacement_is_complete_and_distinct(spark):
    rows = spark.createDataFrame([(i, float(1 + i % 9)) for i in range(300)], "id long, w double")
    items = I.weighted_items(rows, "id", "w").cache()
    got = C.draw_without_replacement(items, 20, 3).collect()
    assert sorted(r["rank"] for r in got) == list(range(1, 21)) and len({r["id"] for r in got}) == 20
    assert C.draw_without_replacement(items, 400, 3).count() == 300
