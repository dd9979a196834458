"""Power-of-two weight classes, the count tree, and output-sensitive sampling.

Classes partition the items by weight within a factor of two.  A query splits its draws
binomially down a tree over the classes, then down trees inside the classes, and stops
where no draw is left, so its work follows the number of distinct results.
"""

from __future__ import annotations

import math
from decimal import Decimal

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.variates import binomial_node, exp_key, hash_uniform, hypergeometric_node, py_uniform
from .items import UNITS, Stats, weight_stats
from .prefix import block_prefix_sum, blocks_for

#: Items in one chunk of a class: the unit that one task samples from.
CHUNK = 1_000_000
E1 = math.e / (math.e - 1)


def with_class(items: DataFrame, least: int) -> DataFrame:
    """Adds ``wclass``: the number of doublings from the least weight, by integer compares."""
    ratio = F.floor(F.log2(F.col("units").cast("double") / float(least))).cast("int")
    low = F.lit(Decimal(least)).cast(UNITS)
    power = lambda k: (low * F.pow(F.lit(2.0), k).cast("decimal(19,0)")).cast(UNITS)
    exact = F.when(F.col("units") < power(F.col("_r")), F.col("_r") - 1).when(F.col("units") >= power(F.col("_r") + 1), F.col("_r") + 1).otherwise(F.col("_r"))
    return items.withColumn("_r", ratio).withColumn("wclass", exact.cast("int")).drop("_r")


def weight_classes(items: DataFrame, stats: Stats | None = None) -> DataFrame:
    """(wclass, n_g, units_g): at most log2(U) + 1 rows, by one aggregate."""
    stats = stats or weight_stats(items)
    return with_class(items, stats.least).groupBy("wclass").agg(F.count("*").alias("n_g"), F.sum("units").cast(UNITS).alias("units_g"))


def class_table(items: DataFrame, stats: Stats) -> list[tuple[int, int, int]]:
    return sorted((r["wclass"], r["n_g"], int(r["units_g"])) for r in weight_classes(items, stats).collect())


def split_counts(weights: list[int], k: int, seed: int, name: str = "node") -> list[int]:
    """k draws split over leaves down a balanced binary tree, each node with its own variate.

    Leaves are padded to a power of two; node (level, index) uses '<name>:level:index'; an
    empty or weightless subtree is not entered.
    """
    size = 1 << max(0, (len(weights) - 1).bit_length())
    leaves = weights + [0] * (size - len(weights))
    sums = [leaves]
    while len(sums[-1]) > 1:
        below = sums[-1]
        sums.append([below[i] + below[i + 1] for i in range(0, len(below), 2)])
    counts = [k]
    for level in range(len(sums) - 1, 0, -1):
        nxt = []
        for ix, m in enumerate(counts):
            left, whole = sums[level - 1][2 * ix], sums[level][ix]
            m_left = binomial_node(m, left / whole, seed, f"{name}:{level}:{ix}") if m and whole else 0
            nxt += [m_left, m - m_left]
        counts = nxt
    return counts[: len(weights)]


# ---- with replacement -------------------------------------------------------------------


def sample_weights(weights: np.ndarray, m: int, rng: np.random.Generator, cutoff: int = 128, dedup: bool = True, gapless: bool = False) -> tuple[np.ndarray, np.ndarray, int]:
    """(positions, multiplicities, nodes visited) of m draws from weights within a factor of two.

    Level by level down an implicit tree; a node with one draw, or with fewer than
    ``cutoff`` draws and at least half as many items, draws straight from its buckets:
    by rejection, or without rejection in ``gapless`` buckets (an inverse search on the
    running sum).  ``dedup`` merges repeats of such a node, as a hash map would.
    """
    n = len(weights)
    run = np.concatenate([[0.0], np.cumsum(weights, dtype=float)])
    lo, hi, cnt = np.array([0]), np.array([n]), np.array([m])
    pos_parts, mult_parts, visited = [], [], 0
    while len(lo):
        visited += len(lo)
        leaf = hi - lo == 1
        if leaf.any():
            pos_parts.append(lo[leaf])
            mult_parts.append(cnt[leaf])
        flat = ~leaf & ((cnt == 1) | ((cnt < cutoff) & (cnt <= 2 * (hi - lo))))
        if flat.any():
            a, b = np.repeat(lo[flat], cnt[flat]), np.repeat(hi[flat], cnt[flat])
            if gapless:
                goal = run[a] + rng.random(len(a)) * (run[b] - run[a])
                got = np.clip(np.searchsorted(run, goal, side="right") - 1, a, b - 1)
            else:
                got, todo = np.empty(len(a), np.int64), np.arange(len(a))
                top = weights.max()
                while len(todo):
                    try_ = a[todo] + (rng.random(len(todo)) * (b[todo] - a[todo])).astype(np.int64)
                    good = rng.random(len(todo)) * top < weights[try_]
                    got[todo[good]] = try_[good]
                    todo = todo[~good]
            if dedup:
                got, times = np.unique(got, return_counts=True)
            else:
                times = np.ones(len(got), np.int64)
            pos_parts.append(got)
            mult_parts.append(times)
        go = ~leaf & ~flat
        lo, hi, cnt = lo[go], hi[go], cnt[go]
        mid = (lo + hi) // 2
        share = (run[mid] - run[lo]) / np.maximum(run[hi] - run[lo], 1e-300)
        left = rng.binomial(cnt, np.clip(share, 0, 1))
        lo, hi, cnt = np.concatenate([lo, mid]), np.concatenate([mid, hi]), np.concatenate([left, cnt - left])
        keep = cnt > 0
        lo, hi, cnt = lo[keep], hi[keep], cnt[keep]
    if not pos_parts:
        return np.empty(0, np.int64), np.empty(0, np.int64), visited
    return np.concatenate(pos_parts), np.concatenate(mult_parts), visited


def chunked(items: DataFrame, stats: Stats, chunk: int = CHUNK) -> DataFrame:
    """Items with class and chunk: what a persisted structure is partitioned by."""
    return with_class(items, stats.least).withColumn("chunk", F.pmod(F.xxhash64("id"), F.lit(max(1, -(-stats.n // chunk)))).cast("int"))


def draw_with_replacement(items: DataFrame, k: int, seed: int = 7, cutoff: int = 128, dedup: bool = True, gapless: bool = False, top: str = "classes", chunk: int = CHUNK, nodes: bool = False) -> DataFrame:
    """(id, k_i): k independent weighted draws as multiplicities.

    ``top`` is ``classes`` (tree over weight classes) or ``workers`` (tree over workers that
    each hold a mix of classes, then their classes).  Only chunks with a positive count
    take part; their counts are the only thing sent out.  Without ``dedup`` an item's
    multiplicity may be split over several rows.  ``nodes`` gives (wclass, chunk, distinct,
    visited) instead: how many tree nodes the distinct results took.
    """
    stats = weight_stats(items)
    rows = chunked(items, stats, chunk)
    if top == "workers":
        rows = rows.withColumn("chunk", F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(max(4, -(-stats.n // chunk)))).cast("int"))
    sums = sorted(((r["chunk"], r["wclass"]) if top == "workers" else (r["wclass"], r["chunk"]), int(r["u"])) for r in rows.groupBy("wclass", "chunk").agg(F.sum("units").alias("u")).collect())
    outer = sorted({key[0] for key, _ in sums}) if top == "workers" else list(range(max((key[0] for key, _ in sums), default=-1) + 1))
    weight = {o: sum(u for key, u in sums if key[0] == o) for o in outer}
    counts = dict(zip(outer, split_counts([weight[o] for o in outer], k, seed), strict=True))
    plan = []
    for o in outer:
        own = [(key[1], u) for key, u in sums if key[0] == o]
        if not own:
            continue
        for (inner, _), m in zip(own, split_counts([u for _, u in own], counts[o], seed, f"inner:{o}"), strict=True):
            if m:
                plan.append((*((inner, o) if top == "workers" else (o, inner)), m))
    asked = F.broadcast(items.sparkSession.createDataFrame(plan, "wclass int, chunk int, m long"))
    kind = items.schema["id"].dataType.simpleString()

    def run(group: pa.Table) -> pa.Table:
        order = group.sort_by("id")
        w = order.column("units").cast(pa.float64()).to_numpy()
        g, c, m = (order.column(x)[0].as_py() for x in ("wclass", "chunk", "m"))
        rng = np.random.Generator(np.random.Philox(key=[seed, (g << 32) + c]))
        at, times, visited = sample_weights(w, m, rng, cutoff, dedup, gapless)
        if nodes:
            return pa.table({"wclass": pa.array([g], pa.int32()), "chunk": pa.array([c], pa.int32()), "distinct": pa.array([len(np.unique(at))], pa.int64()), "visited": pa.array([visited], pa.int64())})
        return pa.table({"id": order.column("id").take(pa.array(at)), "k_i": pa.array(times, pa.int64())})

    made = "wclass int, chunk int, distinct long, visited long" if nodes else f"id {kind}, k_i long"
    return rows.join(asked, ["wclass", "chunk"]).groupBy("wclass", "chunk").applyInArrow(run, made)


def worker_counts(items: DataFrame, k: int, workers: int, seed: int = 7) -> DataFrame:
    """(shard, m): how many of k draws each worker serves; derived by all from p sums alone."""
    sums = {r["shard"]: int(r["u"]) for r in items.groupBy("shard").agg(F.sum("units").alias("u")).collect()}
    counts = split_counts([sums.get(s, 0) for s in range(workers)], k, seed, "worker")
    return items.sparkSession.createDataFrame(list(enumerate(counts)), "shard int, m long")


def uniform_counts(n: int, k: int, parts: int, seed: int = 7, replace: bool = True) -> list[int]:
    """Samples per part of a uniform sample of k out of n by divide and conquer.

    With replacement the left half gets a binomial share, without a hypergeometric one;
    every node has its own variate, so all parts agree without a message.
    """
    def down(lo: int, hi: int, m: int, level: int) -> list[int]:
        if hi - lo == 1:
            return [m]
        mid = (lo + hi) // 2
        a, b = n * mid // parts - n * lo // parts, n * hi // parts - n * mid // parts
        node = f"uniform:{level}:{lo}"
        if replace:
            left = binomial_node(m, a / max(1, a + b), seed, node)
        else:
            left = hypergeometric_node(a, b, m, seed, node)
        return down(lo, mid, left, level + 1) + down(mid, hi, m - left, level + 1)

    return down(0, parts, k, 0)


def worker_alias_draw(items: DataFrame, k: int, workers: int, seed: int = 7) -> DataFrame:
    """(shard, draw, id): the tree over workers fixes how many draws each serves; each serves
    them from its own alias table, without a message to any other."""
    from .alias import alias_by_shard, pick

    counts = F.broadcast(worker_counts(items, k, workers, seed))
    local = alias_by_shard(items, "sweep")
    local = local.withColumn("bucket", (F.row_number().over(Window.partitionBy("shard").orderBy("id")) - 1).cast("long"))
    sizes = items.groupBy("shard").agg(F.count("*").alias("n"))
    asked = counts.where("m > 0").join(F.broadcast(sizes), "shard").select("shard", "n", F.explode(F.sequence(F.lit(0).cast("long"), F.col("m") - 1)).alias("draw"))
    bucket = F.least((hash_uniform(seed, F.lit("own"), F.col("shard"), F.col("draw")) * F.col("n")).cast("long"), F.col("n") - 1)
    asked = asked.select("shard", "draw", bucket.alias("bucket"), hash_uniform(seed, F.lit("owncoin"), F.col("shard"), F.col("draw")).alias("u"))
    return local.join(asked, ["shard", "bucket"]).select("shard", "draw", pick(F.col("u"), F.col("part"), F.col("cap"), F.col("id"), F.col("alias")).alias("id"))


def sequential_draws(items: DataFrame, k: int, seed: int = 7, portable: bool = False) -> DataFrame:
    """(draw, id): all draws by one task from one sequentially built table; the baseline of query speed.

    ``portable`` draws from the swept table with the md5 variates that ``draw_alias`` uses.
    """
    from .alias import alias_sequential

    kind = items.schema["id"].dataType.simpleString()

    def run(group: pa.Table) -> pa.Table:
        order = group.sort_by("id")
        n = order.num_rows
        part, cap = (order.column(c).cast(pa.float64()).to_numpy() for c in ("part", "cap"))
        if portable:
            at = np.array([min(int(py_uniform(seed, f"bucket:{i}") * n), n - 1) for i in range(k)])
            coin = np.array([py_uniform(seed, f"coin:{i}") for i in range(k)])
        else:
            rng = np.random.Generator(np.random.Philox(key=[seed, 2]))
            at, coin = rng.integers(0, n, k), rng.random(k)
        own, other = order.column("id").take(pa.array(at)), order.column("alias").take(pa.array(at))
        take = pc.and_(pa.array(coin * cap[at] >= part[at]), pc.is_valid(other))
        return pa.table({"draw": pa.array(np.arange(k)), "id": pc.if_else(take, other, own)})

    table = alias_sequential(items, "sweep" if portable else "classic").withColumn("_one", F.lit(0))
    return table.groupBy("_one").applyInArrow(run, f"draw long, id {kind}")


def sample_load(draws: DataFrame, shards: int, seed: int = 0) -> DataFrame:
    """(shard, draws, distinct): how draws spread over workers that hold items by random allocation."""
    shard = F.least(F.floor(hash_uniform(seed, F.lit("shard"), F.col("id")) * shards), F.lit(shards - 1)).cast("int")
    return draws.groupBy(shard.alias("shard")).agg(F.count("*").alias("draws"), F.countDistinct("id").alias("distinct"))


def inverse_cdf_draw(items: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """(draw, id): as-of lookup of k uniform points in the running weight; the library baseline."""
    from .prefix import next_at_or_after

    stats = weight_stats(items)
    run = block_prefix_sum(items, "id", {"upto": F.col("units")}, blocks_for(stats.n))
    point = F.ceil(hash_uniform(seed, F.lit("cdf"), F.col("draw")) * float(stats.total)).cast(UNITS)
    asked = items.sparkSession.range(k).withColumnRenamed("id", "draw").withColumn("point", point)
    return next_at_or_after(asked, run.select("id", "upto"), "point", "upto", ["id"], strict=False, blocks=blocks_for(stats.n)).select("draw", F.col("found_id").alias("id"))


def distinct_ratio(items: DataFrame, k: int) -> Column:
    """Expected s / k in closed form, as an aggregate over items with ``units``."""
    total = float(weight_stats(items).total)
    p = F.col("units").cast("double") / total
    return F.sum(1 - F.exp(k * F.log1p(-p))) / k


# ---- without replacement ----------------------------------------------------------------


def clocks(items: DataFrame, k: int, seed: int = 7, form: str = "exponential") -> DataFrame:
    """(id, rank): the k smallest exponential clocks, or the same by the largest powers R^(1/w).

    A top-k keeps k rows a task; only these meet.
    """
    u = hash_uniform(seed, F.col("id"))
    key = {"exponential": exp_key(u, F.col("w")), "power": -F.pow(u, 1 / F.col("w")), "uniform": u}[form]
    top = items.select("id", key.alias("_key")).orderBy("_key", "id").limit(k)
    return top.withColumn("rank", F.row_number().over(Window.orderBy("_key", "id"))).select("id", "rank")


def distinct_bound(classes: list[tuple[int, int, int]], least: int, ell: float) -> float:
    """t of ell draws from classes: light classes by share, heavy classes by number."""
    total = sum(u for *_, u in classes)
    return sum(min(ell * u / total, n) if ell * (least << g) * 2 > total > ell * (least << g) else (n if ell * (least << g) >= total else ell * u / total) for g, n, u in classes)


def choose_ell(classes: list[tuple[int, int, int]], least: int, k: int, virtual_top: bool = True) -> int | None:
    """Number of draws that should give at least k distinct items; None if none can.

    Candidates: W / a_g for each class (classes from g up are then certain to count by
    number), the solution between two classes, and a class above the top where all weight
    counts by share.  The least of them is taken.
    """
    n, total = sum(c[1] for c in classes), sum(c[2] for c in classes)
    need = 2 * k * E1
    found = []
    if virtual_top and math.ceil(need) <= total / (2 * (least << classes[-1][0])):
        found.append(math.ceil(need))
    units = count = 0  # of the lighter classes
    for ix, (g, n_g, u_g) in enumerate(classes):
        ell = -(-total // (least << g))
        if ell * units / total + (n - count) >= need:
            found.append(ell)
        if ix and units:
            lighter = classes[ix - 1][0]
            gap = math.ceil((need - (n - count)) * total / units)
            if total / (least << g) <= gap <= total / (2 * (least << lighter)):
                found.append(gap)
        units, count = units + u_g, count + n_g
    return min(found) if found else None


def choose_ell_stepwise(items: DataFrame, stats: Stats, k: int) -> int | None:
    """The same number by one small aggregate per class: the search that sums per step."""
    rows = with_class(items, stats.least)
    classes = []
    for g in range(stats.classes + 1):
        r = rows.where(F.col("wclass") == g).agg(F.count("*").alias("n"), F.sum("units").alias("u")).first()
        if r.n:
            classes.append((g, r.n, int(r.u)))
    return choose_ell(classes, stats.least, k)


def draw_without_replacement(items: DataFrame, k: int, seed: int = 7, retry: str = "extend", rounds: int = 20, select: bool = False) -> DataFrame:
    """(id, rank): k distinct items, output-sensitive.

    Draws with replacement until k distinct items are there and ranks them by clocks on
    their multiplicities.  A round that falls short is kept as the next ranks and another
    round fills the rest (``extend``); ``discard`` throws it away and repeats, which
    conditions the result.  ``select`` cuts the distinct items down to k by distributed
    selection instead of a top-k.
    """
    from .order import select_threshold

    stats = weight_stats(items)
    spark = items.sparkSession
    if k >= stats.n:
        return clocks(items, stats.n, seed)
    ell = choose_ell(class_table(items, stats), stats.least, k)
    if ell is None:
        return clocks(items, k, seed)
    done, have = None, 0
    for r in range(rounds):
        drawn = draw_with_replacement(items, ell, seed * 1000 + r).groupBy("id").agg(F.sum("k_i").alias("k_i"))
        if done is not None:
            drawn = drawn.join(done, "id", "left_anti")
        key = exp_key(hash_uniform(seed, F.lit(f"round{r}"), F.col("id")), F.col("k_i"))
        ranked = drawn.select("id", key.alias("_key"))
        if select and (limit := select_threshold(ranked, "_key", k - have, finish=0)[0]) is not None:
            ranked = ranked.where(F.col("_key") <= limit)
        part = ranked.orderBy("_key", "id").limit(k - have)
        part = part.withColumn("rank", F.row_number().over(Window.orderBy("_key", "id")) + have).select("id", "rank")
        rows = part.collect()  # at most k rows of ids
        if retry == "discard" and len(rows) < k:
            continue
        part = spark.createDataFrame(rows, part.schema)
        done = part if done is None else done.unionByName(part)
        have += len(rows)
        if have >= k:
            return done
    rest = items.join(done, "id", "left_anti") if done is not None else items
    tail = clocks(rest, k - have, seed).withColumn("rank", F.col("rank") + have)
    return tail if done is None else done.unionByName(tail)


def without_by_rejection(numbered_table: DataFrame, n: int, k: int, seed: int = 7, rounds: int = 40) -> DataFrame:
    """(id, rank): alias draws in order, repeats rejected; the baseline for k well below n."""
    from .alias import draw_alias

    draws = 2 * k + 10
    for _ in range(rounds):
        first = draw_alias(numbered_table, draws, n, seed).groupBy("id").agg(F.min("draw").alias("draw"))
        if first.limit(k).count() >= k:
            top = first.orderBy("draw").limit(k)
            return top.select("id", F.row_number().over(Window.orderBy("draw")).alias("rank"))
        draws *= 2
    raise ValueError("too few distinct items within the rounds allowed")
