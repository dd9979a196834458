"""Other one-item structures: rejection tables, compressed bit words, two-level tables."""

from __future__ import annotations

import math
from decimal import Decimal

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.stored import materialise
from ..functions.variates import hash_uniform
from .alias import alias_by_shard, draw_alias, pick, sweep_rows
from .items import UNITS, weight_stats
from .prefix import block_prefix_sum, blocks_for, next_at_or_after

TRIES = 12


# ---- constant-ratio buckets and the uncompressed rejection table -------------------------


def draw_rejection_flat(items: DataFrame, k: int, seed: int = 7, tries: int = TRIES) -> DataFrame:
    """(draw, id, tries): one item per bucket, accepted with probability w / w_max.

    Meant for weights within a constant factor; the attempts of a draw are rows of a
    round index, and the first accepted one counts.  Draws that a round leaves open go
    on in a further one of twice the attempts, until none is open.
    """
    stats = weight_stats(items)
    dense = block_prefix_sum(items, "id", {"bucket": F.lit(1)}, blocks_for(stats.n)).withColumn("bucket", (F.col("bucket") - 1).cast("long"))
    found, first, draws = None, 0, None
    while True:
        asked = attempts(items, k, tries, stats.n, seed, first, draws)
        hit = dense.join(F.broadcast(asked) if k <= 100_000 else asked, "bucket").where(F.col("u") * float(stats.most) <= F.col("units").cast("double"))
        won = hit.groupBy("draw").agg(F.min(F.struct("attempt", "id")).alias("f")).select("draw", F.col("f.id").alias("id"), (F.col("f.attempt") + 1).alias("tries"))
        won = materialise(won)
        found = won if found is None else found.unionByName(won)
        if not stats.n or found.count() == k:
            return found
        draws = items.sparkSession.range(k).withColumnRenamed("id", "draw").join(found, "draw", "left_anti")
        first, tries = first + tries, 2 * tries


def attempts(df: DataFrame, k: int, tries: int, n: int, seed: int, first: int = 0, draws: DataFrame | None = None) -> DataFrame:
    draws = df.sparkSession.range(k).withColumnRenamed("id", "draw") if draws is None else draws
    draws = draws.withColumn("attempt", F.explode(F.sequence(F.lit(first), F.lit(first + tries - 1))))
    position = F.least((hash_uniform(seed, F.lit("try"), F.col("draw"), F.col("attempt")) * n).cast("long"), F.lit(n - 1))
    return draws.select("draw", "attempt", position.alias("bucket"), hash_uniform(seed, F.lit("accept"), F.col("draw"), F.col("attempt")).alias("u"))


def copies(items: DataFrame, n: int, total: int) -> DataFrame:
    """Adds ``c`` = ceil(n w / W) buckets of width W / n, and their running sum ``c1``."""
    mass = (F.col("units") * F.lit(n).cast("decimal(18,0)")).cast(UNITS)
    whole = F.lit(Decimal(total)).cast(UNITS)
    over = F.col("mass") % whole
    c = (F.col("mass") - over) / whole + F.when(over == 0, 0).otherwise(1)
    rows = items.withColumn("mass", mass).withColumn("c", c.cast("long"))
    return block_prefix_sum(rows, "id", {"c1": F.col("c")}, blocks_for(n)).withColumn("c1", F.col("c1").cast("long"))


def rejection_table(items: DataFrame) -> DataFrame:
    """(bucket, id, fill, cap): item i owns ceil(n w / W) buckets, the last partly filled; at most 2n."""
    stats = weight_stats(items)
    rows = copies(items, stats.n, stats.total).select("id", "mass", "c", (F.col("c1") - F.col("c")).alias("c0"), F.explode(F.sequence(F.lit(1), F.col("c"))).alias("j"))
    cap = F.lit(Decimal(stats.total)).cast(UNITS)
    fill = F.when(F.col("j") < F.col("c"), cap).otherwise((F.col("mass") - cap * (F.col("c") - 1)).cast(UNITS)).cast(UNITS)
    return rows.select((F.col("c0") + F.col("j") - 1).alias("bucket"), "id", fill.alias("fill"), cap.alias("cap"))


def draw_rejection(table: DataFrame, buckets: int, k: int, seed: int = 7, tries: int = 40) -> DataFrame:
    """(draw, id): a uniform bucket, accepted with its fill; success is at least 1/2 a try."""
    asked = attempts(table, k, tries, buckets, seed)
    hit = table.join(F.broadcast(asked) if k * tries <= 1_000_000 else asked, "bucket").where(F.col("u") * F.col("cap").cast("double") <= F.col("fill").cast("double"))
    return hit.groupBy("draw").agg(F.min(F.struct("attempt", "id")).alias("f")).select("draw", F.col("f.id").alias("id"))


# ---- compressed: start bits and a rank directory ------------------------------------------

WORD = 32


def compressed_build(items: DataFrame, r: int = 1) -> tuple[DataFrame, DataFrame]:
    """(words, entries): words (word_ix, bits, ones_before) mark where each entry's buckets start.

    ``entries`` (rank, members): r neighbouring items packed in one entry, drawn inside by
    a scan.  With r = 1 an entry is one item.
    """
    stats = weight_stats(items)
    dense = block_prefix_sum(items, "id", {"_r": F.lit(1)}, blocks_for(stats.n)).withColumn("rank", F.floor((F.col("_r") - 1) / r).cast("long"))
    members = dense.groupBy("rank").agg(F.sort_array(F.collect_list(F.struct("id", "units"))).alias("members"), F.sum("units").cast(UNITS).alias("units"))
    n = -(-stats.n // r)
    entry = copies(members.withColumnRenamed("rank", "id"), n, stats.total).withColumnRenamed("id", "rank")
    start = F.col("c1") - F.col("c")
    bits = entry.select(F.floor(start / WORD).cast("long").alias("word_ix"), F.pmod(start, F.lit(WORD)).cast("int").alias("pos"))
    words = bits.groupBy("word_ix").agg(F.bit_or(F.expr("shiftleft(1L, pos)")).alias("bits"))
    words = block_prefix_sum(words, "word_ix", {"_o": F.bit_count("bits")}, blocks_for(n))
    words = words.select("word_ix", "bits", (F.col("_o") - F.bit_count("bits")).cast("long").alias("ones_before"))
    return words, entry.select("rank", "members", "mass", "units", "c", "c1", F.lit(Decimal(stats.total)).cast(UNITS).alias("cap"))


def compressed_draw(words: DataFrame, entries: DataFrame, buckets: int, k: int, seed: int = 7, tries: int = 40) -> DataFrame:
    """(draw, id): uniform bucket, rank by counting start bits, partial last buckets by a coin."""
    asked = attempts(words, k, tries, buckets, seed).withColumn("word_ix", F.floor(F.col("bucket") / WORD).cast("long")).withColumn("pos", F.pmod("bucket", F.lit(WORD)).cast("int"))
    # a word without a start bit is absent: the last start lies in the word before
    have = F.broadcast(asked) if k * tries <= 1_000_000 else asked
    upto = F.bit_count(F.col("bits").bitwiseAND(F.expr("shiftleft(1L, pos + 1) - 1")))
    direct = have.join(words, "word_ix", "left")
    missing = direct.where("bits is null").select("draw", "attempt", "bucket", "u", "word_ix")
    # however far before: the next word after counts the starts up to there, the last word all of them
    after = next_at_or_after(missing, words, "word_ix", "word_ix", ["ones_before"], True)
    ones = words.agg(F.sum(F.bit_count("bits"))).first()[0]
    filled = after.select("draw", "attempt", "bucket", "u", (F.coalesce("found_ones_before", F.lit(ones)) - 1).alias("rank"))
    ranked = direct.where("bits is not null").select("draw", "attempt", "bucket", "u", (F.col("ones_before") + upto - 1).alias("rank")).unionByName(filled)
    hit = ranked.join(entries, "rank")
    last = F.col("bucket") == F.col("c1") - 1
    fill = (F.col("mass") - F.col("cap") * (F.col("c") - 1)).cast("double")
    ok = hit.where(~last | (F.col("u") * F.col("cap").cast("double") <= fill))
    first = ok.groupBy("draw").agg(F.min(F.struct("attempt", "rank")).alias("f")).select("draw", F.col("f.rank").alias("rank"))
    chosen = first.join(entries.select("rank", "members", "units"), "rank")
    goal = hash_uniform(seed, F.lit("inside"), F.col("draw")) * F.col("units").cast("double")
    scan = F.aggregate("members", F.struct(F.lit(0.0).alias("s"), F.lit(None).cast(entries.schema["members"].dataType.elementType["id"].dataType).alias("id")), lambda a, m: F.struct((a["s"] + m["units"].cast("double")).alias("s"), F.when(a["id"].isNull() & (a["s"] + m["units"].cast("double") >= goal), m["id"]).otherwise(a["id"]).alias("id")))
    return chosen.select("draw", F.coalesce(scan["id"], F.element_at("members", -1)["id"]).alias("id"))


# ---- two levels ----------------------------------------------------------------------------


def meta_weights(items: DataFrame) -> DataFrame:
    """(shard, n_items, units) of each shard: the top level's items."""
    return items.groupBy("shard").agg(F.count("*").alias("n_items"), F.sum("units").cast(UNITS).alias("units"))


def top_table(meta: DataFrame) -> list[tuple[int, int, int | None, int]]:
    """(shard, part, alias, cap) of the replicated top level; built on the driver from p rows."""
    rows = sorted((r["shard"], int(r["units"])) for r in meta.collect())
    cap, p = sum(u for _, u in rows), len(rows)
    masses = [(s, u * p) for s, u in rows]
    made = sweep_rows([m for m in masses if m[1] <= cap], [m for m in masses if m[1] > cap], cap)
    return sorted((s, part, a, cap) for s, part, a in made)


def sqrt_shards(items: DataFrame, n: int) -> DataFrame:
    """Adds ``shard``: blocks of about sqrt(n) items in id order."""
    width = max(1, math.isqrt(n))
    return block_prefix_sum(items, "id", {"_r": F.lit(1)}, blocks_for(n)).withColumn("shard", F.floor((F.col("_r") - 1) / width).cast("int")).drop("_r")


def twolevel_build(items: DataFrame, base: str = "sweep") -> tuple[DataFrame, DataFrame]:
    """(top, local): the replicated top table and the shards' tables with bucket numbers."""
    top = top_table(meta_weights(items))
    spark = items.sparkSession
    rows = [(i, s, Decimal(p), a, Decimal(c)) for i, (s, p, a, c) in enumerate(top)]
    local = alias_by_shard(items, base)
    local = local.withColumn("bucket", (F.row_number().over(Window.partitionBy("shard").orderBy("id")) - 1).cast("long"))
    return spark.createDataFrame(rows, f"bucket long, id int, part {UNITS}, alias int, cap {UNITS}"), local


def twolevel_draw(top: DataFrame, local: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """(draw, shard, id): a shard from the top table, then a draw delegated to its table."""
    p = top.count()
    shard = draw_alias(top, k, p, seed).withColumnRenamed("id", "shard")
    sizes = local.groupBy("shard").agg(F.count("*").alias("m"))
    asked = shard.join(F.broadcast(sizes), "shard")
    bucket = F.least((hash_uniform(seed, F.lit("local"), F.col("draw")) * F.col("m")).cast("long"), F.col("m") - 1)
    asked = asked.select("draw", "shard", bucket.alias("bucket"), hash_uniform(seed, F.lit("localcoin"), F.col("draw")).alias("u"))
    joined = local.join(F.broadcast(asked) if k <= 100_000 else asked, ["shard", "bucket"])
    return joined.select("draw", "shard", pick(F.col("u"), F.col("part"), F.col("cap"), F.col("id"), F.col("alias")).alias("id"))


def overlay(free: list[tuple[int, int]], mass: list[tuple[int, int]]) -> list[tuple[int, int, int]]:
    """(taker, giver, amount): lay free intervals and mass intervals on one line and overlap them."""
    out, i, j = [], 0, 0
    free, mass = [list(x) for x in free if x[1] > 0], [list(x) for x in mass if x[1] > 0]
    while i < len(free) and j < len(mass):
        amount = min(free[i][1], mass[j][1])
        out.append((free[i][0], mass[j][0], amount))
        free[i][1] -= amount
        mass[j][1] -= amount
        i, j = i + (free[i][1] == 0), j + (mass[j][1] == 0)
    return out


def twoalias_pieces(meta: DataFrame) -> DataFrame:
    """(bucket, owner, piece): every bucket holds W / p, of its own light mass and at most two heavy pieces."""
    rows = sorted((r["shard"], int(r["units"])) for r in meta.collect())
    p, cap = len(rows), sum(u for _, u in rows)
    light = [(s, u * p) for s, u in rows if u * p <= cap]
    heavy = [(s, u * p) for s, u in rows if u * p > cap]
    free = sorted([(s, cap - m) for s, m in light] + [(s, cap) for s, _ in heavy])
    pieces = [(s, s, m) for s, m in light] + overlay(free, heavy)
    return meta.sparkSession.createDataFrame([(b, o, Decimal(x)) for b, o, x in pieces], f"bucket int, owner int, piece {UNITS}")


def twoalias_draw(pieces: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """(draw, shard): a uniform bucket, then a comparison with its at most three pieces."""
    rows = pieces.groupBy("bucket").agg(F.sort_array(F.collect_list(F.struct("owner", "piece"))).alias("p"), F.sum("piece").cast(UNITS).alias("cap"))
    ids = sorted(r["bucket"] for r in rows.select("bucket").collect())
    spark = pieces.sparkSession
    index = spark.createDataFrame(list(enumerate(ids)), "ix long, bucket int")
    asked = spark.range(k).select(F.col("id").alias("draw"), F.least((hash_uniform(seed, F.lit("bucket"), F.col("id")) * len(ids)).cast("long"), F.lit(len(ids) - 1)).alias("ix"), hash_uniform(seed, F.lit("coin"), F.col("id")).alias("u"))
    x = asked.join(F.broadcast(index), "ix").join(F.broadcast(rows), "bucket").withColumn("t", F.col("u") * F.col("cap").cast("double"))
    w = lambda i: F.coalesce(F.get("p", F.lit(i))["piece"].cast("double"), F.lit(0.0))
    return x.select("draw", F.when(F.col("t") <= w(0), F.get("p", F.lit(0))["owner"]).when((F.col("t") <= w(0) + w(1)) | (F.size("p") == 2), F.get("p", F.lit(1))["owner"]).otherwise(F.get("p", F.lit(2))["owner"]).alias("shard"))


def rebalance_heavy(items: DataFrame, shards: int, c: float = 1.0) -> DataFrame:
    """(shard, id, piece): items above c W / (p log p) are cut and spread over free capacity.

    Ordinary items stay.  Only the few super-heavy items and p loads reach the driver.
    """
    stats = weight_stats(items)
    limit = c * stats.total / (shards * max(1.0, math.log2(shards)))
    big = [(r["id"], int(r["units"]) * shards) for r in items.where(F.col("units") > F.lit(limit)).orderBy("id").collect()]
    small = items.where(F.col("units") <= F.lit(limit))
    load = {r["shard"]: int(r["u"]) * shards for r in small.groupBy("shard").agg(F.sum("units").alias("u")).collect()}
    free = [(s, max(0, stats.total - load.get(s, 0))) for s in range(shards)]
    short = sum(m for _, m in big) - sum(f for _, f in free)
    if short > 0:
        free = [(s, f + -(-short // shards)) for s, f in free]
    pieces = [(s, i, Decimal(x)) for s, i, x in overlay(free, big)]
    kind = items.schema["id"].dataType.simpleString()
    moved = items.sparkSession.createDataFrame(pieces, f"shard int, id {kind}, piece {UNITS}")
    kept = small.select("shard", "id", (F.col("units") * shards).cast(UNITS).alias("piece"))
    return kept.unionByName(moved)


def load_profile(df: DataFrame, weight: Column) -> DataFrame:
    """(shard, items, load) of an allocation."""
    return df.groupBy("shard").agg(F.count("*").alias("items"), F.sum(weight).alias("load"))

