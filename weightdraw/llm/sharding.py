"""Balanced label propagation of documents into shards (operator 4).

Documents with equal texts are linked.  The law is ``rows``: shard counts are at most one
apart, from the first assignment on and after every round.

* Start: rows are numbered without gaps (hash blocks, block offsets, number in the block)
  and dealt round robin, which is exactly even and ignores links.
* Round: every group of linked rows counts its members per shard; members outside the
  group's strongest shard with room for the rest want to move there.  The wishes form a shards x shards table of
  counts (the only thing the driver sees).  Wishes are granted as far as each shard's
  surplus can be met by unlinked rows that give way; these fill the places left behind,
  so all sizes stay as they are.  Wishes of the strongest groups go first.
* A group larger than half a shard is dealt into parts by row number, each part being a
  group of its own, so it fills a few shards instead of touching all.
* Rounds end when no wish is granted, or after ``rounds``.

Slots number a shard's rows from 0 without gaps: hash blocks again, so no task ever
sorts a shard.

Defined results for odd rows: a null text has size 16, checksum 0 and no links; empty
texts are equal texts; repeated rows are separate, linked rows; a null doc_id is dealt
like any other; fewer rows than shards leave shards empty; an empty table gives an
empty result.  Extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import materialise, ship

OVERHEAD = 16
#: Rows in a hash block: what one window task sorts.
BLOCK_ROWS = 20_000


def numbered(rows: DataFrame, within: list[str], spread: Column, n: int, name: str) -> DataFrame:
    """Adds ``name``: gapless numbers from 0 within the columns ``within``.

    Two levels: blocks of the hash ``spread`` get offsets by a window over block counts
    (a small table), rows a number inside their block.
    """
    blocks = max(1, math.ceil(n / BLOCK_ROWS))
    rows = rows.withColumn("_b", F.pmod(spread, F.lit(blocks)))
    counts = rows.groupBy(*within, "_b").agg(F.count("*").alias("_n"))
    order = Window.partitionBy(*within).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    start = counts.select(*within, "_b", F.coalesce(F.sum("_n").over(order), F.lit(0)).alias("_start"))
    inner = Window.partitionBy(*within, "_b").orderBy(spread)
    return rows.withColumn("_r", F.row_number().over(inner)).join(start, [*within, "_b"]).withColumn(name, F.col("_start") + F.col("_r") - 1).drop("_b", "_r", "_start")


def grants(wish: dict[tuple[int, int], int], free: dict[int, int], shards: int) -> tuple[dict, dict, dict]:
    """(granted wishes, rows that give way per shard, places left per shard).

    A shard may take in more than it loses only by as much as it has unlinked rows.
    """
    got = dict(wish)
    while True:
        net = [0] * shards
        for (i, j), k in got.items():
            net[j] += k
            net[i] -= k
        over = next((j for j in range(shards) if net[j] > free.get(j, 0)), None)
        if over is None:
            return got, {j: x for j, x in enumerate(net) if x > 0}, {j: -x for j, x in enumerate(net) if x < 0}
        cut = net[over] - free.get(over, 0)
        for i, j in sorted(got, key=lambda p: -got[p]):
            if j == over and cut:
                less = min(cut, got[i, j])
                got[i, j] -= less
                cut -= less


def _table(df: DataFrame, rows: list[tuple], schema: str) -> DataFrame:
    return F.broadcast(df.sparkSession.createDataFrame(rows, schema))


def balanced_shards(docs: DataFrame, shards: int = 40, rounds: int = 10) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard (null: not the key law)."""
    text = F.col("text").cast("string")
    rows = docs.select(
        "doc_id",
        (F.coalesce(F.octet_length(text), F.lit(0)) + OVERHEAD).cast("long").alias("size"),
        F.crc32(F.coalesce(text, F.lit("")).cast("binary")).alias("text_crc32"),
        F.when(text.isNotNull(), F.xxhash64(text)).alias("h1"),
        F.when(text.isNotNull(), F.xxhash64(F.lit(1), text, F.length(text))).alias("h2"),
    )
    rows = materialise(rows)
    n = rows.count()
    cap = max(1, n // shards)
    groups = rows.where("h1 is not null").groupBy("h1", "h2").agg(F.count("*").alias("members")).where("members > 1")
    rows = numbered(rows.join(groups, ["h1", "h2"], "left"), [], F.xxhash64("doc_id", "h1", "h2"), n, "g")
    part = F.when(F.col("members") * 2 > cap, F.pmod(F.xxhash64("g"), F.ceil(F.col("members") * 2 / cap))).otherwise(0)
    state = materialise(rows.withColumn("shard", F.pmod("g", F.lit(shards)).cast("int")).withColumn("part", F.when(F.col("members").isNotNull(), part)).drop("members"))
    group = ["h1", "h2", "part"]
    for _ in range(rounds):
        linked = state.where("part is not null")
        held = linked.groupBy(*group, "shard").agg(F.count("*").alias("k"))
        unlinked = state.where("part is null").select("g", "shard")
        free = {r["shard"]: r["count"] for r in unlinked.groupBy("shard").count().collect()}
        room = F.array(*[F.lit(free.get(j, 0)) for j in range(shards)])
        # at most one entry a shard; shards that can take the whole part come first
        at = held.groupBy(*group).agg(F.collect_list(F.struct("k", "shard")).alias("at"), F.sum("k").alias("total"))
        fits = lambda x: (F.element_at(room, x["shard"] + 1) >= F.col("total") - x["k"]).cast("int")
        best = F.array_max(F.transform("at", lambda x: F.struct(fits(x).alias("fits"), x["k"].alias("k"), F.pmod(F.xxhash64("h1", x["shard"]), F.lit(997)).alias("tie"), x["shard"].alias("shard"))))
        best = at.select(*group, best.alias("best")).select(*group, F.col("best.shard").alias("to"), F.col("best.k").alias("k"))
        wishes = materialise(linked.join(best, group).where("shard != to").select("g", F.col("shard").alias("from"), "to", "k"))
        wish = {(r["from"], r["to"]): r["count"] for r in wishes.groupBy("from", "to").count().collect()}
        if not wish:
            break
        got, away, left = grants(wish, free, shards)
        if not sum(got.values()):
            break
        quota = _table(state, [(i, j, k) for (i, j), k in got.items() if k], "from int, to int, quota long")
        turn = Window.partitionBy("from", "to").orderBy(F.desc("k"), "g")
        moves = wishes.join(quota, ["from", "to"]).withColumn("r", F.row_number().over(turn)).where("r <= quota").select("g", F.col("to").alias("new"))
        if away:
            # rows that give way, numbered over all shards, meet the places left in order
            lo, gives = 0, []
            for j, k in sorted(away.items()):
                gives.append((j, k, lo))
                lo += k
            lo, takes = 0, []
            for j, k in sorted(left.items()):
                takes.append((j, lo, lo + k))
                lo += k
            able = unlinked.join(_table(state, gives, "shard int, quota long, base long"), "shard")
            able = numbered(able, ["shard"], F.xxhash64("g"), n, "r").where("r < quota").withColumn("at", F.col("base") + F.col("r"))
            place = _table(state, takes, "new int, lo long, hi long")
            moves = moves.unionByName(able.join(place, F.expr("at >= lo and at < hi")).select("g", "new"))
        state = materialise(state.join(moves, "g", "left").withColumn("shard", F.coalesce("new", "shard")).drop("new"))
    out = numbered(state, ["shard"], F.xxhash64("g", F.lit(3)), n, "slot")
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def cut_edges(assigned: DataFrame) -> DataFrame:
    """Groups of equal texts (by checksum and size) and the shards they touch: the objective."""
    per = assigned.groupBy("text_crc32", "size").agg(F.count("*").alias("members"), F.countDistinct("shard").alias("touched"))
    return per.where("members > 1").agg(F.count("*").alias("n_groups"), F.sum(F.expr("touched - 1")).alias("extra_shards"))


ship(__name__)
