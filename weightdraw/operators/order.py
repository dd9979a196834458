"""Weighted permutations and distributed selection."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.stored import materialise
from ..functions.variates import exp_key, hash_uniform
from .items import weight_stats
from .prefix import block_prefix_sum, blocks_for

# ---- permutation ------------------------------------------------------------------------


def integer_key(v: Column, n: int, w_max: float, w_min: float) -> Column:
    """n ln(v n w_max), floored; -1 below 0 and one top value beyond the expected range.

    It is computed from the clock v, so it is a monotone function of it.
    """
    top = math.ceil(n * math.log(max(math.e, n * (w_max / w_min) * (math.log(max(n, 2)) + 8))))
    x = F.floor(n * F.log(v * n * w_max))
    return F.when(x < 0, F.lit(-1)).when(x >= top, F.lit(top)).otherwise(x).cast("long")


def weighted_permutation(items: DataFrame, seed: int = 7, method: str = "sort", blocks: int | None = None) -> DataFrame:
    """(id, pos): a weighted random order of all items, positions from 0.

    ``sort`` orders by the clock; ``bucketed`` by the integer key first (an integer sort,
    whose ranges need no sampling pass) and by the clock inside a bucket.  Both give the
    same order.  Positions are block prefix sums, never a single-task window.
    """
    stats = weight_stats(items)
    ends = items.agg(F.max("w").alias("hi"), F.min("w").alias("lo")).first()
    rows = items.select("id", exp_key(hash_uniform(seed, F.col("id")), F.col("w")).alias("v"))
    k = blocks_for(stats.n, blocks)
    if method == "sort":
        out = block_prefix_sum(rows, "v", {"pos": F.lit(1)}, k, tie="id")
        return out.select("id", (F.col("pos") - 1).cast("long").alias("pos"))
    rows = rows.withColumn("ikey", integer_key(F.col("v"), stats.n, ends.hi, ends.lo))
    # range blocks of the integer key from its known law: no look at the data
    hi = math.log(max(math.e, stats.n * (ends.hi / ends.lo) * (math.log(max(stats.n, 2)) + 8)))
    block = F.floor(F.greatest(F.col("ikey"), F.lit(0)) / (stats.n * hi / k)).cast("int")
    rows = rows.withColumn("_b", F.least(block, F.lit(k - 1)))
    sizes = {r["_b"]: r["count"] for r in rows.groupBy("_b").count().collect()}
    start, base = 0, []
    for b in range(k):
        base.append(start)
        start += sizes.get(b, 0)
    inside = F.row_number().over(Window.partitionBy("_b").orderBy("ikey", "v", "id"))
    return rows.select("id", (F.element_at(F.array(*[F.lit(x) for x in base]), F.col("_b") + 1) + inside - 1).cast("long").alias("pos"))


def bucket_occupancy(items: DataFrame, seed: int = 7) -> DataFrame:
    """(size, n_buckets): how many items share an integer key; expected at most 1/e others."""
    stats = weight_stats(items)
    ends = items.agg(F.max("w").alias("hi"), F.min("w").alias("lo")).first()
    key = integer_key(exp_key(hash_uniform(seed, F.col("id")), F.col("w")), stats.n, ends.hi, ends.lo)
    return items.select(key.alias("ikey")).groupBy("ikey").count().groupBy(F.col("count").alias("size")).agg(F.count("*").alias("n_buckets"))


# ---- selection ----------------------------------------------------------------------------

#: Candidate keys small enough to finish on the driver.
FINISH = 1_000


def select_threshold(df: DataFrame, key: str, k: int, pivots: int = 8, finish: int = FINISH, stored: bool = False) -> tuple[float | None, int]:
    """(k-th smallest key, rounds): each round counts rows at or below some pivots in one aggregate.

    Keys are computed once and written (unless ``stored``: they are a table already); a round takes pivots from an approximate quantile
    sketch of the open interval, placed around the rank still looked for, counts at all of
    them together and goes on with what lies between two.  More pivots, fewer rounds.
    Pivots stand further apart than the sketch errs, so the rank lies between two near
    ones however small it is among the rows, and every round leaves a small share of them.
    """
    accuracy = 200 if pivots == 1 else 2000
    rows = df.select(F.col(key).cast("double").alias("v")).where("v is not null")
    rows = rows if stored else materialise(rows)
    size = rows.count()
    if size < k or k < 1:
        return None, 0
    lo, hi, below, rounds = -math.inf, math.inf, 0, 0
    while size > finish:
        rounds += 1
        part = rows.where((F.col("v") > lo) & (F.col("v") <= hi))
        at = (k - below) / size
        # a single pivot goes a little beyond the rank, on the side that leaves less
        one = min(1.0, max(0.0, at + (0.01 + 2 / size) * (1 if at <= 0.5 else -1)))
        step = max(3 * math.sqrt(at * (1 - at) / size + 1 / size**2), 3 / accuracy)
        spread = [one] if pivots == 1 else [min(1.0, max(0.0, at + (i - (pivots - 1) / 2) * step)) for i in range(pivots)]
        marks = sorted(set(part.agg(F.percentile_approx("v", spread, accuracy).alias("p")).first()["p"]))
        got = part.agg(*[F.count_if(F.col("v") <= m).alias(f"c{i}") for i, m in enumerate(marks)]).first()
        upto = [(-math.inf, 0), *((m, got[f"c{i}"]) for i, m in enumerate(marks)), (math.inf, size)]
        new_lo, under = max((x for x in upto if below + x[1] < k), key=lambda x: x[0])
        new_hi, over = min((x for x in upto if below + x[1] >= k), key=lambda x: x[0])
        if over - under == size:
            break
        lo, hi, below, size = max(lo, new_lo), min(hi, new_hi), below + under, over - under
    last = rows.where((F.col("v") > lo) & (F.col("v") <= hi)).orderBy("v").limit(k - below)
    return last.agg(F.max("v")).first()[0], rounds


def select_range(df: DataFrame, key: str, low: int, high: int) -> tuple[float, int]:
    """(a key, its rank) with rank between low and high: a sketch and one count to verify."""
    n = df.count()
    accuracy = max(100, int(2 * n / max(1, high - low)))
    for _ in range(4):
        mark = df.agg(F.percentile_approx(key, (low + high) / 2 / n, accuracy)).first()[0]
        rank = df.where(F.col(key) <= mark).count()
        if low <= rank <= high:
            return mark, rank
        accuracy *= 4
    mark, _ = select_threshold(df, key, (low + high) // 2)
    return mark, (low + high) // 2


def smallest(df: DataFrame, key: str, k: int) -> DataFrame:
    """The k smallest keys, unsorted selection: a top-k per task, then of tasks."""
    return df.orderBy(key).limit(k)


def res_split(df: DataFrame, key: str, x: float) -> tuple[DataFrame, DataFrame]:
    """Ordered-set split: rows up to x, rows above."""
    return df.where(F.col(key) <= x), df.where(F.col(key) > x)


def res_rank(df: DataFrame, key: str, x: float) -> int:
    return df.where(F.col(key) <= x).count()


def res_select(df: DataFrame, key: str, r: int) -> float | None:
    return df.orderBy(key).limit(r).agg(F.max(key)).first()[0]
