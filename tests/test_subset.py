"""Walks of gaps over many parts, and workers at the bounds of their ranges."""

import math

import pytest
from pyspark.sql import functions as F

from weightdraw.functions.variates import py_uniform
from weightdraw.operators import subset as P


def walk(n, cap, seed, name, group):
    at, t, found = -1, 0, []
    while True:
        t += 1
        u = py_uniform(seed, f"{name}:{group}:0:{t}")
        at += 1 + (0 if cap >= 1 else math.floor(math.log(u) / math.log1p(-cap)))
        if at >= n:
            return found
        found.append((group, t, at))


@pytest.mark.parametrize("chunk", [64, 1_000, 1_000_000])
def test_a_class_is_one_walk_however_many_parts(spark, chunk):
    groups = [(0, 5_000, 0.1), (1, 700, 1.0), (2, 3, 0.01), (5, 40_000, 0.003)]
    hits = P.skips(spark, groups, 7, "skip", chunk)
    want = sorted(x for g, n, c in groups for x in walk(n, c, 7, "skip", g))
    assert sorted((r.pclass, r.t, r.pos) for r in hits.where("part = 0").collect()) == want


def test_worker_just_below_a_bound(spark):
    pi = [0.999999, *[1.0] * 23, 0.000001]
    rows = spark.createDataFrame(list(enumerate(pi)), "id long, pi double")
    got = [r.worker for r in P.poisson_assign(rows, 8).orderBy("id").collect()]
    units, before, want = [round(p * 1_000_000) for p in pi], 0, []
    for u in units:
        want.append(before * 8 // sum(units))
        before += u
    assert want[3] == 0 and got == want


def test_assign_of_nothing(spark):
    assert P.poisson_assign(spark.range(0).select("id", F.lit(0.5).alias("pi")), 4).count() == 0
