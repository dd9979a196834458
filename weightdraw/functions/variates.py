"""Hash variates: every random number is a function of (seed, stream, key).

``hash_uniform`` is the portable backend (md5, bit-equal in other SQL engines);
``fast_uniform`` (xxhash64) is the production one.  Neither depends on the layout of
partitions, so a retried task draws the same numbers.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

TWO52 = float(1 << 52)


def _parts(seed: int, *key: Column | str | int) -> list[Column]:
    return [F.lit(str(seed)), *[k.cast("string") if isinstance(k, Column) else F.lit(str(k)) for k in key]]


def hash_uniform(seed: int, *key: Column | str | int) -> Column:
    """Uniform on (0, 1]: (first 13 hex digits of md5('seed:key:...') + 1) / 2^52."""
    digest = F.md5(F.concat_ws(":", *_parts(seed, *key)).cast("binary"))
    return (F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") + 1) / TWO52


def fast_uniform(seed: int, *key: Column | str | int) -> Column:
    """Uniform on (0, 1] from xxhash64; the same contract, not portable to other engines."""
    bits = F.shiftrightunsigned(F.xxhash64(F.lit(seed), *[k if isinstance(k, Column) else F.lit(k) for k in key]), 12)
    return (bits.cast("double") + 1) / TWO52


def sql_uniform(seed: int, key: str) -> str:
    """The DuckDB text of ``hash_uniform`` for an SQL string expression ``key``."""
    return f"((('0x' || substr(md5('{seed}:' || {key}), 1, 13))::BIGINT + 1) / 4503599627370496.0)"


def py_uniform(seed: int, key: str) -> float:
    """The driver's copy of ``hash_uniform``."""
    import hashlib

    return (int(hashlib.md5(f"{seed}:{key}".encode()).hexdigest()[:13], 16) + 1) / TWO52  # noqa: S324


def exp_key(uniform: Column, weight: Column) -> Column:
    """Exponential clock -ln(u) / w: the k smallest are a weighted sample without replacement."""
    return -F.log(uniform) / weight


def binomial_inverse(m: int, p: float, u: float) -> int:
    """Smallest x whose cumulative Binomial(m, p) probability reaches u, by log-gamma terms."""
    if m <= 0 or p <= 0:
        return 0
    if p >= 1:
        return m
    total, lp, lq, lm = 0.0, math.log(p), math.log1p(-p), math.lgamma(m + 1)
    for x in range(m):
        total += math.exp(lm - math.lgamma(x + 1) - math.lgamma(m - x + 1) + x * lp + (m - x) * lq)
        if total >= u:
            return x
    return m


def binomial_node(m: int, p: float, seed: int, node: str) -> int:
    """The count at a tree node: inverse CDF up to 10^4 draws, a Philox stream of the node beyond."""
    if m <= 10_000:
        return binomial_inverse(m, p, py_uniform(seed, node))
    bits = int(py_uniform(seed, node) * TWO52)
    return int(np.random.Generator(np.random.Philox(key=[seed, bits])).binomial(m, min(max(p, 0.0), 1.0)))


def hypergeometric_node(good: int, bad: int, m: int, seed: int, node: str) -> int:
    """How many of m items without replacement are among ``good`` of good + bad; the node's own
    variate, by inverse CDF up to 10^4 draws and by a Philox stream of the node beyond."""
    low, high = max(0, m - bad), min(m, good)
    if low >= high:
        return low
    if m > 10_000:
        bits = int(py_uniform(seed, node) * TWO52)
        return int(np.random.Generator(np.random.Philox(key=[seed, bits])).hypergeometric(good, bad, m))
    choose = lambda n, k: math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)
    whole, total, u = choose(good + bad, m), 0.0, py_uniform(seed, node)
    for x in range(low, high):
        total += math.exp(choose(good, x) + choose(bad, m - x) - whole)
        if total >= u:
            return x
    return high
