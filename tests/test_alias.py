"""Alias tables: every build agrees with the sequential sweep and conserves mass."""

import random

import pytest

from weightdraw.operators import alias as A
from weightdraw.operators import items as I

random.seed(3)
CASES = {
    "ambiguous_split": [1, 5, 3],
    "thirteen": [3, 9, 4, 12, 7, 5, 11, 2, 10, 6, 8, 14, 1],
    "one": [9],
    "equal": [7, 7, 7, 7],
    "giant": [10**12] + [1] * 30,
    "at_capacity": [2, 4, 6],
}


def items_of(spark, weights):
    rows = spark.createDataFrame([(i, float(w)) for i, w in enumerate(weights)], "id long, w double")
    return I.weighted_items(rows, "id", "w")


def table(df):
    return sorted((r.id, int(r.part), r.alias) for r in df.collect())


@pytest.mark.parametrize("name", CASES)
def test_builds_agree(spark, name):
    items = items_of(spark, CASES[name]).cache()
    stats = I.weight_stats(items)
    want = table(A.alias_sequential(items, "sweep"))
    assert table(A.alias_asof(items, blocks=3)) == want
    assert table(A.alias_splitpack(items, 3, blocks=2)) == want
    greedy = A.alias_greedy(items, 2)
    assert greedy.count() == stats.n
    assert A.mass_check(greedy, items, stats).where("not mass_ok").count() == 0


def brute_state(weights, cut):
    """Light and heavy buckets among the first ``cut`` of the sweep."""
    n, cap = len(weights), sum(weights)
    heavy = {i for i, w in enumerate(weights) if w * n > cap}
    rows = list(A.sweep_rows([(i, w * n) for i, w in enumerate(weights) if i not in heavy], [(i, weights[i] * n) for i in sorted(heavy)], cap))
    done = [r[0] for r in rows[:cut]]
    return sum(i not in heavy for i in done), sum(i in heavy for i in done)


def test_split_takes_the_larger_heavy_count(spark):
    for weights in ([1, 5, 3], [random.randint(1, 40) for _ in range(23)]):
        items = items_of(spark, weights)
        stats = I.weight_stats(items)
        cuts = list(range(1, len(weights)))
        for cut, light, heavy, _ in A.split_states(A.ranked(items, stats), stats, cuts, block=4):
            assert (light, heavy) == brute_state(weights, cut)


def test_random_sweeps_conserve_mass():
    for _ in range(500):
        w = [random.randint(1, 50) for _ in range(random.randint(1, 12))]
        n, cap = len(w), sum(w)
        pairs = [(i, x * n) for i, x in enumerate(w)]
        for rows in (A.sweep_rows([p for p in pairs if p[1] <= cap], [p for p in pairs if p[1] > cap], cap), A.classic_rows(pairs, cap)):
            mass, buckets = dict.fromkeys(range(n), 0), 0
            for ident, part, other in rows:
                mass[ident] += part
                buckets += 1
                if other is not None:
                    mass[other] += cap - part
                else:
                    assert part == cap
            assert buckets == n and mass == dict(pairs)


def test_invalid_weights(spark):
    rows = spark.createDataFrame([(1, None), (2, float("nan")), (3, -1.0), (4, 0.0), (5, float("inf")), (6, 2.5)], "id long, w double")
    assert [r.id for r in I.weighted_items(rows, "id", "w", 10).collect()] == [6]
    with pytest.raises(ValueError, match="5 rows"):
        I.weighted_items(rows, "id", "w", strict=True)
