"""Poisson (subset) samples: every item independently with its own probability."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.stored import materialise
from ..functions.variates import hash_uniform
from .prefix import block_prefix_sum, blocks_for


#: Gaps of a walk that one task draws.
CHUNK = 1_000_000


def inclusion_items(df: DataFrame, id_col, pi) -> DataFrame:
    """(id, pi) with 0 < pi <= 1; a probability above 1 is an error, 0 and null are left out."""
    rows = df.select(id_col.alias("id"), pi.cast("double").alias("pi"))
    if rows.where("pi > 1").limit(1).count():
        raise ValueError("inclusion probabilities must not exceed 1")
    return rows.where("pi > 0")


def poisson_naive(items: DataFrame, seed: int = 7) -> DataFrame:
    """(id): one coin per item, a filter in the scan's stage."""
    return items.where(hash_uniform(seed, F.col("id")) <= F.col("pi")).select("id")


def poisson_classes(items: DataFrame, n: int) -> DataFrame:
    """Adds ``pclass``: i for pi in (2^-(i+1), 2^-i], the last class takes the rest."""
    last = max(1, math.ceil(math.log2(max(2, n))))
    raw = F.floor(-F.log2("pi")).cast("int")
    return items.withColumn("pclass", F.least(F.when(F.pow(F.lit(2.0), -raw.cast("double")) < F.col("pi"), raw - 1).when(F.pow(F.lit(2.0), -(raw + 1).cast("double")) >= F.col("pi"), raw + 1).otherwise(raw), F.lit(last)))


def class_caps(items: DataFrame) -> list[tuple[int, int, float]]:
    """(class, size, cap) with cap the largest probability of the class; log n rows."""
    return sorted((r["pclass"], r["n"], r["cap"]) for r in items.groupBy("pclass").agg(F.count("*").alias("n"), F.max("pi").alias("cap")).collect())


def skips(spark, groups: list[tuple[int, int, float]], seed: int, name: str = "skip", chunk: int = CHUNK) -> DataFrame:
    """(pclass, part, t, pos, cap): positions hit by geometric gaps, class by class.

    A class is one walk (part 0), whose gap t is a hash of t alone: parts of ``chunk`` gaps
    are summed first, one row a part reaches the driver, and every part runs from the sum of
    those before it, by its own task.  Expected hits and six deviations more are drawn at
    once; a class whose walk has not passed its end goes on with twice as many, until all have.
    """
    tries = {g: math.ceil(n * c + 6 * math.sqrt(n * c) + 10) for g, n, c in groups}
    keep = lambda x: F.greatest(F.lit(0), F.least(F.lit(chunk), x)).cast("long")
    u = hash_uniform(seed, F.lit(name), F.col("pclass"), F.col("part"), F.col("t"))
    gap = F.when(F.col("cap") >= 1, F.lit(0)).otherwise(F.floor(F.log(u) / F.log1p(-F.col("cap")))).cast("long") + 1
    made = "pclass int, part long, n long, cap double, step long, tries long"

    def gaps(before: dict[tuple[int, int], int] | None = None) -> DataFrame:
        rows = [(g, 0, n, float(c), i, tries[g]) for g, n, c in groups for i in range(-(-tries[g] // chunk))]
        wide = spark.createDataFrame([(*r, before[r[0], r[4]]) for r in rows if before[r[0], r[4]] < r[2]] if before else rows, made + (", start long" if before else ""))
        # a part is one row until here: dealt out, so its gaps are drawn by a task of its own
        wide = wide.repartition(max(1, min(len(rows), 1_000)), "pclass", "step")
        first = F.col("step") * chunk
        walk = wide.where("tries > 0").select("*", F.explode(F.sequence(first + 1, first + keep(F.col("tries") - first))).alias("t"))
        return walk.withColumn("_g", gap)

    while True:
        sums = {(r["pclass"], r["step"]): r["s"] for r in gaps().groupBy("pclass", "step").agg(F.sum("_g").alias("s")).collect()}
        short, before = [], {}
        for g, n, _ in groups:
            at = 0
            for i in range(-(-tries[g] // chunk)):
                before[g, i] = at
                at += sums[g, i]
            if at < n:
                short.append(g)
        if not short:
            break
        tries |= {g: 2 * tries[g] for g in short}
    run = F.sum("_g").over(Window.partitionBy("pclass", "step").orderBy("t").rowsBetween(Window.unboundedPreceding, 0))
    walk = gaps(before).withColumn("pos", F.col("start") + run - 1)
    return walk.where("pos < n").select("pclass", "part", "t", "pos", "cap")


def poisson_sample(items: DataFrame, seed: int = 7) -> DataFrame:
    """(id): output-sensitive; skips at the class cap, then acceptance with pi / cap.

    Positions are dense inside a class (by id), so a persisted, class-partitioned table is
    read at the hit positions only.
    """
    n = items.count()
    rows = materialise(poisson_classes(items, n))
    caps = class_caps(rows)
    if not caps:
        return items.select("id")
    dense = class_positions(rows, [g for g, *_ in caps], blocks_for(n))
    hits = skips(items.sparkSession, caps, seed)
    joined = dense.join(hits, ["pclass", "pos"])
    return joined.where(hash_uniform(seed, F.lit("acc"), F.col("pclass"), F.col("part"), F.col("t")) * F.col("cap") <= F.col("pi")).select("id")


def class_positions(rows: DataFrame, classes: list[int], blocks: int) -> DataFrame:
    """Adds ``pos``: dense numbers from 0 in id order inside each class, all classes in one pass."""
    counts = {f"_n{g}": F.when(F.col("pclass") == g, 1).otherwise(0) for g in classes}
    run = block_prefix_sum(rows, "id", counts, blocks)
    own = F.coalesce(*[F.when(F.col("pclass") == g, F.col(f"_n{g}")) for g in classes])
    return run.withColumn("pos", (own - 1).cast("long")).drop(*counts)


def bernoulli_skips(spark, n: int, q: float, seed: int = 7) -> DataFrame:
    """(pos): an unweighted Bernoulli sample of 0..n-1 by geometric gaps."""
    return skips(spark, [(0, n, q)], seed, "bernoulli").select("pos")


def bernoulli_items(items: DataFrame, q: float, seed: int = 7) -> DataFrame:
    """The items at the positions of an unweighted Bernoulli sample, positions in id order."""
    n = items.count()
    dense = block_prefix_sum(items, "id", {"pos": F.lit(1)}, blocks_for(n)).withColumn("pos", (F.col("pos") - 1).cast("long"))
    return dense.join(bernoulli_skips(items.sparkSession, n, q, seed), "pos").drop("pos")


def poisson_assign(items: DataFrame, workers: int, scale: int = 1_000_000) -> DataFrame:
    """(id, worker): worker i owns the running probability range [(i-1) W / p, i W / p)."""
    rows = items.withColumn("_u", F.round(F.col("pi") * scale).cast("long"))
    total = rows.agg(F.sum("_u")).first()[0] or 1
    run = block_prefix_sum(rows, "id", {"run": F.col("_u")}, blocks_for(items.count()))
    run = run.withColumn("_at", ((F.col("run") - F.col("_u")) * workers).cast("decimal(38,0)"))
    # whole division: a quotient of decimals is rounded to six places, up to the next worker
    at = F.expr(f"_at div cast({int(total)} as decimal(38,0))")
    return run.select("id", F.least(at, F.lit(workers - 1)).cast("int").alias("worker"))


def compact(df: DataFrame) -> DataFrame:
    """(id, pos): the sample in a gapless array."""
    return block_prefix_sum(df, "id", {"pos": F.lit(1)}, 8).select("id", (F.col("pos") - 1).cast("long").alias("pos"))


def poisson_per_shard(items: DataFrame, seed: int = 7) -> DataFrame:
    """(id, shard): every shard samples its own rows with its own classes; no message at all."""
    kind = items.schema["id"].dataType.simpleString()

    def run(group: pa.Table) -> pa.Table:
        order = group.sort_by("id")
        pi, shard = order.column("pi").to_numpy(), order.column("shard")[0].as_py()
        rng = np.random.Generator(np.random.Philox(key=[seed, shard]))
        cls = np.minimum(np.floor(-np.log2(pi)).astype(int), max(1, math.ceil(math.log2(max(2, len(pi))))))
        taken = []
        for g in np.unique(cls):
            own = np.flatnonzero(cls == g)
            cap = pi[own].max()
            if cap >= 1:
                at = np.arange(len(own))
            else:
                at, pos = [], -1
                while True:
                    pos += 1 + int(np.log(1 - rng.random()) / np.log1p(-cap))
                    if pos >= len(own):
                        break
                    at.append(pos)
                at = np.array(at, np.int64)
            taken.append(own[at[rng.random(len(at)) * cap <= pi[own[at]]]])
        at = np.sort(np.concatenate(taken)) if taken else np.empty(0, np.int64)
        return pa.table({"id": order.column("id").take(pa.array(at)), "shard": pa.array([shard] * len(at), pa.int32())})

    return items.groupBy("shard").applyInArrow(run, f"id {kind}, shard int")


def pps_fixed_inclusion(items: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """(id, certain): k items with inclusion probability exactly k w / W; another law than clocks.

    Items whose probability would exceed 1 are certain (the set is iterated to its fixed
    point); the rest is a systematic draw along the running weight.
    """
    from .items import weight_stats
    from .prefix import next_at_or_after

    stats = weight_stats(items)
    sure, left, total = [], k, stats.total
    while left:
        more = [r["id"] for r in items.where(F.col("units").cast("double") * left >= float(total)).where(~F.col("id").isin(sure) if sure else F.lit(True)).select("id", "units").collect()]
        if not more:
            break
        sure += more
        gone = items.where(F.col("id").isin(sure)).agg(F.sum("units")).first()[0]
        left, total = k - len(sure), stats.total - int(gone)
    certain = items.where(F.col("id").isin(sure)) if sure else items.limit(0)
    rest = items.where(~F.col("id").isin(sure)) if sure else items
    if left <= 0 or total <= 0:
        return certain.limit(k).select("id", F.lit(True).alias("certain"))
    from ..functions.variates import py_uniform

    run = block_prefix_sum(rest, "id", {"upto": F.col("units")}, blocks_for(stats.n))
    start = py_uniform(seed, "systematic")
    points = items.sparkSession.range(left).select(F.col("id").alias("draw"), F.ceil((F.col("id") + start) * (total / left)).cast("decimal(38,0)").alias("point"))
    points = points.withColumn("point", F.least("point", F.lit(total).cast("decimal(38,0)")))
    drawn = next_at_or_after(points, run.select("id", "upto"), "point", "upto", ["id"], False, blocks_for(stats.n))
    return certain.select("id", F.lit(True).alias("certain")).unionByName(drawn.select(F.col("found_id").alias("id"), F.lit(False).alias("certain")))
