"""Alias tables: sequential builds, the closed form of the sweep, packets, and draws.

A table has one row per bucket: (bucket, id, part, alias, cap).  Capacity is
W = sum of units and an item's mass n * units, so no division occurs; a bucket belongs
to ``id`` with the share part / cap and to ``alias`` with the rest.
"""

from __future__ import annotations

from collections.abc import Iterator
from decimal import Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.stored import materialise
from ..functions.variates import hash_uniform
from .items import UNITS, Stats, classify, weight_stats
from .prefix import block_prefix_sum, blocks_for, boundaries, with_block

WIDE = pa.decimal128(38, 0)
#: Draw requests (24 bytes each and overhead) that may be broadcast.
BROADCAST_DRAWS = 200_000
#: Chunks of neighbouring items up to which their cut points are literals from a sample.
CUT_CHUNKS = 4_000


# ---- sequential builds, on Python integers ---------------------------------------------


def sweep_rows(light: list[tuple[object, int]], heavy: list[tuple[object, int]], cap: int, first: int | None = None, closed: int | None = None) -> Iterator[tuple[object, int, object]]:
    """(id, part, alias) by sweeping light and heavy items once, in order.

    The current heavy item tops up light buckets while it holds more than a bucket; then
    its own bucket takes what is left of it and the next heavy item fills that up.
    ``first`` is what an earlier packet left of the first heavy item; only the first
    ``closed`` heavy items get buckets here (the one after fills, and is closed later).
    """
    closed = len(heavy) if closed is None else closed
    i = j = 0
    left = (heavy[0][1] if first is None else first) if heavy else 0
    while i < len(light) or j < closed:
        if i < len(light) and (left > cap or j >= closed):
            name, mass = light[i]
            i += 1
            yield name, mass, heavy[j][0] if j < len(heavy) and mass < cap else None
            left -= cap - mass
        else:
            follow = heavy[j + 1] if j + 1 < len(heavy) else None
            yield heavy[j][0], left, follow[0] if follow and left < cap else None
            if follow:
                left = follow[1] - (cap - left)
            j += 1


def classic_rows(items: list[tuple[object, int]], cap: int) -> Iterator[tuple[object, int, object]]:
    """(id, part, alias) by the two-stack method: pair a light item with a heavy one, put the rest back."""
    small = [x for x in items if x[1] <= cap]
    large = [x for x in items if x[1] > cap]
    while small and large:
        name, mass = small.pop()
        donor, rest = large.pop()
        yield name, mass, donor if mass < cap else None
        rest -= cap - mass
        (large if rest > cap else small).append((donor, rest))
    for name, mass in [*small, *large]:
        yield name, min(mass, cap), None


def _pack(kind: str) -> object:
    def run(group: pa.Table) -> pa.Table:
        ids, mass, cap = group.column("id").to_pylist(), [int(x) for x in group.column("mass").to_pylist()], int(group.column("cap")[0].as_py())
        rows = sorted(zip(ids, mass, strict=True))
        made = classic_rows(rows, cap) if kind == "classic" else sweep_rows([r for r in rows if r[1] <= cap], [r for r in rows if r[1] > cap], cap)
        return _table(group.column("id").type, group.column("shard")[0].as_py(), list(made), cap)

    return run


def _table(kind: pa.DataType, shard: int, rows: list[tuple[object, int, object]], cap: int) -> pa.Table:
    columns = list(zip(*rows, strict=True)) or [[], [], []]
    return pa.table(
        {
            "shard": pa.array([shard] * len(rows), pa.int32()),
            "id": pa.array(columns[0], kind),
            "part": pa.array([Decimal(x) for x in columns[1]], WIDE),
            "alias": pa.array(columns[2], kind),
            "cap": pa.array([Decimal(cap)] * len(rows), WIDE),
        }
    )


def _kind(items: DataFrame) -> str:
    return items.schema["id"].dataType.simpleString()


def alias_sequential(items: DataFrame, kind: str = "sweep") -> DataFrame:
    """The table built by one task: ``classic`` (the baseline) or ``sweep``."""
    stats = weight_stats(items)
    rows = classify(items, stats).select("id", "mass", F.lit(Decimal(stats.total)).cast(UNITS).alias("cap"), F.lit(0).alias("shard"))
    t = _kind(items)
    return rows.groupBy("shard").applyInArrow(_pack(kind), f"shard int, id {t}, part {UNITS}, alias {t}, cap {UNITS}").drop("shard")


def alias_by_shard(items: DataFrame, kind: str = "sweep") -> DataFrame:
    """One table per value of ``shard``, each built by its own task: the local level of two."""
    per = items.groupBy("shard").agg(F.count("*").alias("_n"), F.sum("units").cast(UNITS).alias("cap"))
    rows = items.join(F.broadcast(per), "shard").select("shard", "id", (F.col("units") * F.col("_n")).cast(UNITS).alias("mass"), "cap")
    t = _kind(items)
    return rows.groupBy("shard").applyInArrow(_pack(kind), f"shard int, id {t}, part {UNITS}, alias {t}, cap {UNITS}")


# ---- the closed form of the sweep: prefix sums and one as-of pass -------------------------


def closed_form(rows: DataFrame, capacity: int, blocks: int) -> DataFrame:
    """(bucket, id, part, alias, cap) of the sweep over masses (id, mass) that fill whole buckets.

    Running deficits d of light items and running excesses e of heavy ones come from one
    pass in id order, written once.  On the axis of both, a light item stands at the
    deficits before it and a heavy one at its excess, heavy first where they meet.  Then
    all that the sweep decides lies behind an item on that axis: the next heavy item is
    the alias, and a heavy item is closed by the bucket whose deficits reach its excess,
    which ends where the next light item stands (or at the total).  It keeps
    cap + e - d.  Two shuffles of narrow rows; one row a block reaches the driver.
    """
    cap = F.lit(Decimal(capacity)).cast(UNITS)
    spark = rows.sparkSession
    rows = rows.select("id", F.col("mass").cast(UNITS).alias("mass")).withColumn("heavy", F.col("mass") > cap)
    zero = F.lit(0).cast(UNITS)
    sums = {"d": F.when(F.col("heavy"), zero).otherwise(cap - F.col("mass")), "e": F.when(F.col("heavy"), F.col("mass") - cap).otherwise(zero), "bucket": F.lit(1)}
    run = block_prefix_sum(rows, "id", sums, blocks)
    at = F.when(F.col("heavy"), F.col("e")).otherwise(F.col("d") - (cap - F.col("mass"))).cast(UNITS)
    run = materialise(run.select((F.col("bucket") - 1).cast("long").alias("bucket"), "id", "mass", "heavy", at.alias("at"), F.col("d").alias("upto")))
    cuts = boundaries(run, "at", blocks)
    axis = with_block(run, "at", cuts)
    ends = axis.groupBy("_block").agg(F.min(F.when(F.col("heavy"), F.struct("at", "id"))).alias("heavy"), F.min(F.when(~F.col("heavy"), F.col("at"))).alias("light"), F.max("upto").alias("upto"))
    ends = {r["_block"]: r for r in ends.collect()}
    whole = max((int(r["upto"]) for r in ends.values()), default=0)
    later, heavy, light = [], None, Decimal(whole)
    for b in range(len(cuts), -1, -1):
        later.append((b, heavy, light))
        if b in ends:
            heavy = ends[b]["heavy"]["id"] if ends[b]["heavy"] else heavy
            light = light if ends[b]["light"] is None else ends[b]["light"]
    t = rows.schema["id"].dataType.simpleString()
    later = F.broadcast(spark.createDataFrame(later, f"_block int, later_heavy {t}, later_light {UNITS}"))
    # backwards, because only a growing frame is evaluated in one pass
    behind = Window.partitionBy("_block").orderBy(F.desc("at"), "heavy").rowsBetween(Window.unboundedPreceding, -1)
    seen = axis.withColumn("_h", F.last(F.when(F.col("heavy"), F.col("id")), ignorenulls=True).over(behind)).withColumn("_l", F.last(F.when(~F.col("heavy"), F.col("at")), ignorenulls=True).over(behind))
    seen = seen.join(later, "_block")
    part = F.when(F.col("heavy"), cap + F.col("at") - F.coalesce("_l", "later_light")).otherwise(F.col("mass")).cast(UNITS)
    out = seen.select("bucket", "id", part.alias("part"), F.coalesce("_h", "later_heavy").alias("alias"))
    return out.select("bucket", "id", "part", F.when(F.col("part") < cap, F.col("alias")).alias("alias"), cap.alias("cap"))


def alias_asof(items: DataFrame, blocks: int | None = None, stats: Stats | None = None) -> DataFrame:
    """The sweep's table without a sequential pass, buckets numbered in id order."""
    stats = stats or weight_stats(items)
    return closed_form(classify(items, stats), stats.total, blocks_for(stats.n, blocks))


# ---- splits and packets ------------------------------------------------------------------


def ranked(items: DataFrame, stats: Stats, blocks: int | None = None) -> DataFrame:
    """Items with class, rank in class (from 1) and running mass in class."""
    return rank_masses(classify(items, stats), blocks_for(stats.n, blocks))


def rank_masses(rows: DataFrame, blocks: int) -> DataFrame:
    """(id, mass, is_heavy, ...) with rank and running mass in the class, by one pass over both classes."""
    heavy = lambda x, h: F.when(F.col("is_heavy") == h, x).otherwise(F.lit(0))
    sums = {"_n0": heavy(F.lit(1), False), "_n1": heavy(F.lit(1), True), "_m0": heavy(F.col("mass"), False), "_m1": heavy(F.col("mass"), True)}
    run = block_prefix_sum(rows, "id", sums, blocks)
    pick_ = lambda a, b: F.when(F.col("is_heavy"), F.col(b)).otherwise(F.col(a))
    return run.withColumn("rank", pick_("_n0", "_n1")).withColumn("prefix", pick_("_m0", "_m1")).drop(*sums)


def split_states(rows: DataFrame, stats: Stats, cuts: list[int], block: int | None = None) -> list[tuple[int, int, int, int]]:
    """(n', light, heavy, spill) of the sweep after n' buckets, for each n' in ``cuts``.

    Block-wise: the driver searches class sums of blocks of ``block`` ranks; what they
    leave open is settled by one filtered job on the few candidate ranks of all splits.
    Of the heavy counts that fit, the largest is taken, and never more light items than
    there are.
    """
    size = block or max(1, stats.n.bit_length())
    sums = rows.groupBy("is_heavy", F.floor((F.col("rank") - 1) / size).alias("b")).agg(F.max("rank").alias("r"), F.max("prefix").alias("p")).collect()
    ends = {h: {int(x.r): int(x.p) for x in sums if x.is_heavy == h} for h in (False, True)}
    count = {h: max(ends[h], default=0) for h in (False, True)}

    def around(h: bool, r: int) -> tuple[int, int]:
        """Bounds of the running mass at rank r from block ends."""
        if r <= 0:
            return 0, 0
        low, high = (r // size) * size, min(-(-r // size) * size, count[h])
        return (ends[h].get(low, 0) if low else 0), ends[h][high]

    open_: dict[int, tuple[int, int]] = {}
    for cut in cuts:
        lo, hi = max(0, cut - count[False]), min(cut, count[True])
        goal = cut * stats.total
        while lo < hi:  # narrow while block sums decide
            mid = (lo + hi + 1) // 2
            (a, b), (c, d) = around(True, mid), around(False, cut - mid)
            if b + d <= goal:
                lo = mid
            elif a + c > goal:
                hi = mid - 1
            else:
                break
        while lo < hi and sum(x[0] for x in (around(True, hi), around(False, cut - hi))) > goal:
            hi -= 1
        while lo < hi and sum(x[1] for x in (around(True, lo + 1), around(False, cut - lo - 1))) <= goal:
            lo += 1
        open_[cut] = lo, hi
    wanted = {h: sorted({r for cut, (lo, hi) in open_.items() for j in range(lo, hi + 2) for r in ([j] if h else [cut - j]) if r > 0}) for h in (False, True)}
    tests = [(h, a, b) for h in (False, True) for a, b in _runs(wanted[h])]
    spans = F.broadcast(rows.sparkSession.createDataFrame(tests or [(False, 0, 0)], "h boolean, a long, b long"))
    got = rows.join(spans, F.expr("is_heavy = h and rank between a and b")).select("is_heavy", F.col("rank").cast("long").alias("rank"), "prefix", "mass").distinct().collect()
    at = {(r.is_heavy, r["rank"]): (int(r.prefix), int(r.mass)) for r in got}
    at[False, 0] = at[True, 0] = 0, 0
    out = []
    for cut, (lo, hi) in open_.items():
        j = max(x for x in range(lo, hi + 1) if x == lo or at[True, x][0] + at[False, cut - x][0] <= cut * stats.total)
        used = at[True, j][0] + at[False, cut - j][0]
        spill = used + at[True, j + 1][1] - cut * stats.total if (True, j + 1) in at else 0
        out.append((cut, cut - j, j, spill))
    return out


def _runs(ranks: list[int]) -> Iterator[tuple[int, int]]:
    start = prev = None
    for r in ranks:
        if start is None:
            start = prev = r
        elif r == prev + 1:
            prev = r
        else:
            yield start, prev
            start = prev = r
    if start is not None:
        yield start, prev


def split_and_pack(rows: DataFrame, n: int, capacity: int, packets: int, block: int | None = None) -> DataFrame:
    """Packs ranked rows (id, mass, is_heavy, rank, prefix) that fill n buckets in independent packets."""
    rows = materialise(rows.select("id", "mass", "is_heavy", "rank", "prefix"))
    cuts = [n * k // packets for k in range(1, packets)]
    states = [(0, 0, 0, None), *split_states(rows, Stats(n, capacity, 0, 0), cuts, block), (n, None, None, None)]
    plan = []
    for k, (a, b) in enumerate(zip(states, states[1:], strict=False)):
        plan.append((k, a[1], b[1] if b[1] is not None else 1 << 60, a[2], b[2] if b[2] is not None else 1 << 60, None if a[3] is None else Decimal(a[3])))
    packet = F.broadcast(rows.sparkSession.createDataFrame(plan, f"packet int, i0 long, i1 long, j0 long, j1 long, spill {UNITS}"))
    # a heavy item also goes to every packet that it only fills: the one after its range
    inside = F.expr("(not is_heavy and rank > i0 and rank <= i1) or (is_heavy and rank > j0 and rank <= j1 + 1)")
    cap = F.lit(Decimal(capacity)).cast(UNITS)
    # where the sweep comes to an item: the deficits, or the excesses, before it; heavy first where they meet
    before = (F.col("prefix") - F.col("mass") - (F.col("rank") - 1) * cap).cast(UNITS)
    routed = rows.join(packet, inside).select("packet", "id", "mass", "is_heavy", F.col("rank").cast("long").alias("rank"), "j1", "spill", F.when(F.col("is_heavy"), before).otherwise(-before).alias("at"))
    routed = routed.repartition(packets, "packet").sortWithinPartitions("packet", "at", F.desc("is_heavy"), "rank")
    t = _kind(rows)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """One pass in the sweep's order, which holds a batch of rows and one open heavy item."""
        sweep = None
        for batch in batches:
            packet_of = batch.column("packet").to_numpy()
            ends = [0, *(np.flatnonzero(np.diff(packet_of)) + 1).tolist(), len(packet_of)]
            for lo, hi in zip(ends, ends[1:], strict=False):
                if lo == hi:
                    continue
                part = batch.slice(lo, hi - lo)
                if sweep is None or sweep.packet != packet_of[lo]:
                    if sweep is not None:
                        yield from sweep.end()
                    sweep = PacketSweep(int(packet_of[lo]), capacity, part)
                yield from sweep.take(part)
        if sweep is not None:
            yield from sweep.end()

    return routed.mapInArrow(pack, f"id {t}, part {UNITS}, alias {t}, cap {UNITS}")


class PacketSweep:
    """``sweep_rows`` over record batches in the order in which the sweep meets the items.

    What the open heavy item still holds changes by mass - cap with every row of either
    class: a light one is topped up from it, and a heavy one fills its bucket and is opened.
    """

    def __init__(self, packet: int, cap: int, first: pa.RecordBatch) -> None:
        self.packet, self.cap = packet, cap
        self.last, spill = first.column("j1")[0].as_py(), first.column("spill")[0].as_py()
        self.kind = first.column("id").type
        self.spill = None if spill is None else int(spill)
        self.open = None  # (id, rank) of the heavy item that fills
        self.left = 0

    def take(self, rows: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        ids, heavy = rows.column("id"), rows.column("is_heavy").to_numpy(zero_copy_only=False)
        mass = np.array([int(x) for x in rows.column("mass").to_pylist()], object)
        change = mass - self.cap
        at = np.flatnonzero(heavy)
        if self.open is None and len(at) and self.spill is not None:
            change[at[0]] = self.spill
        elif self.open is None and len(at):
            change[at[0]] = mass[at[0]]
        run = np.cumsum(np.concatenate([np.array([self.left], object), change]))
        # before the first heavy item of a packet only full buckets come, which change nothing
        names = pa.concat_arrays([pa.array([self.open[0] if self.open else None], self.kind), ids])
        holder = np.maximum.accumulate(np.where(heavy, np.arange(1, len(heavy) + 1), 0))
        light = np.flatnonzero(~heavy)
        part, own, other = mass.copy(), np.arange(1, len(heavy) + 1), holder.copy()
        own[at] = np.concatenate([[0], at[:-1] + 1]) if len(at) else own[at]  # a heavy row closes the one before
        part[at] = run[at]
        other[at] = at + 1
        keep = np.ones(len(heavy), bool)
        if self.open is None and len(at):
            keep[at[0]] = False
        full = np.array(part == self.cap, bool)
        if len(light) + len(at) and keep.any():
            yield self.made(names.take(pa.array(own[keep])), part[keep], pa.array(np.where(full, 0, other)[keep], mask=full[keep]), names)
        if len(at):
            self.open = ids[int(at[-1])].as_py(), rows.column("rank")[int(at[-1])].as_py()
        self.left = run[-1]

    def end(self) -> Iterator[pa.RecordBatch]:
        if self.open and self.open[1] <= self.last:
            yield self.made(pa.array([self.open[0]], self.kind), [self.left], pa.array([None], pa.int64()), pa.array([None], self.kind))

    def made(self, ids: pa.Array, part: list[int], alias: pa.Array, names: pa.Array) -> pa.RecordBatch:
        return pa.record_batch({"id": ids, "part": pa.array([Decimal(x) for x in part], WIDE), "alias": names.take(alias), "cap": pa.repeat(pa.scalar(Decimal(self.cap), WIDE), len(part))})


def alias_splitpack(items: DataFrame, packets: int, block: int | None = None, blocks: int | None = None) -> DataFrame:
    """Split the sweep at n * k / p buckets and pack the p packets independently."""
    stats = weight_stats(items)
    return split_and_pack(ranked(items, stats, blocks), stats.n, stats.total, packets, block)


def class_chunks(items: DataFrame, stats: Stats, width: int) -> tuple[DataFrame, int]:
    """(id, mass, is_heavy, chunk) and the number of chunks, of about ``width`` neighbouring ids each.

    Few chunks are cut at literals, so a filter on them is settled row by row; beyond
    ``CUT_CHUNKS`` a chunk is ``width`` consecutive positions, which reach no driver.
    """
    rows = classify(items, stats).select("id", "mass", "is_heavy")
    count = max(1, stats.n // width)
    if count <= CUT_CHUNKS:
        cuts = boundaries(rows, "id", count)
        return with_block(rows, "id", cuts, "chunk"), len(cuts) + 1
    placed = block_prefix_sum(rows, "id", {"_at": F.lit(1)}, blocks_for(stats.n))
    placed = placed.select("id", "mass", "is_heavy", F.floor((F.col("_at").cast("long") - 1) / width).cast("int").alias("chunk"))
    return materialise(placed), -(-stats.n // width)


def block_states(items: DataFrame, stats: Stats, packets: int, width: int) -> tuple[DataFrame, list[tuple[int, int, int, int]]]:
    """(rows with class and chunk, split states) from sums of ``width`` items instead of item prefixes.

    Only one row a chunk of about ``width`` neighbouring ids and class is summed and
    scanned; a state is settled by the items of the few chunks in which it lies.  Ranks
    and running masses of single items are never written.
    """
    rows, chunks = class_chunks(items, stats, width)
    sums = {(r["is_heavy"], r["chunk"]): (r["k"], int(r["m"])) for r in rows.groupBy("is_heavy", "chunk").agg(F.count("*").alias("k"), F.sum("mass").alias("m")).collect()}
    before: dict[tuple[bool, int], tuple[int, int]] = {}
    whole = {}
    for h in (False, True):
        k = m = 0
        for c in range(chunks):
            before[h, c] = k, m
            a, b = sums.get((h, c), (0, 0))
            k, m = k + a, m + b
        whole[h] = k, m
    carry = F.broadcast(items.sparkSession.createDataFrame([(h, c, k, Decimal(m)) for (h, c), (k, m) in before.items()], f"is_heavy boolean, chunk int, k0 long, m0 {UNITS}"))
    inside = Window.partitionBy("is_heavy", "chunk").orderBy("id").rowsBetween(Window.unboundedPreceding, 0)
    placed = rows.join(carry, ["is_heavy", "chunk"])

    def prefix_at(h: bool, ranks: list[int]) -> dict[int, tuple[int, int]]:
        """Running mass and own mass at some ranks of a class: one job on the chunks that hold them."""
        held = {r: max((c for c in range(chunks) if before[h, c][0] < r), default=0) for r in ranks if 0 < r <= whole[h][0]}
        if not held:
            return {}
        part = placed.where((F.col("is_heavy") == h) & F.col("chunk").isin(sorted(set(held.values()))))
        part = part.withColumn("rank", F.col("k0") + F.row_number().over(inside)).withColumn("prefix", (F.col("m0") + F.sum("mass").over(inside)).cast(UNITS))
        return {r["rank"]: (int(r["prefix"]), int(r["mass"])) for r in part.where(F.col("rank").isin(sorted(held))).select("rank", "prefix", "mass").collect()}

    states = []
    for cut in [stats.n * k // packets for k in range(1, packets)]:
        lo, hi, goal = max(0, cut - whole[False][0]), min(cut, whole[True][0]), cut * stats.total
        while lo < hi:  # each step asks for one heavy and one light rank
            mid = (lo + hi + 1) // 2
            used = prefix_at(True, [mid]).get(mid, (0, 0))[0] + prefix_at(False, [cut - mid]).get(cut - mid, (0, 0))[0]
            lo, hi = (mid, hi) if used <= goal else (lo, mid - 1)
        heavy, light = prefix_at(True, [lo, lo + 1]), prefix_at(False, [cut - lo])
        used = heavy.get(lo, (0, 0))[0] + light.get(cut - lo, (0, 0))[0]
        states.append((cut, cut - lo, lo, used + heavy[lo + 1][1] - goal if lo + 1 in heavy else 0))
    return placed, states


def alias_blockwise(items: DataFrame, packets: int, block: int | None = None) -> DataFrame:
    """Split-and-pack on sums of blocks of neighbouring items (about log2 n by the method, larger in production)."""
    stats = weight_stats(items)
    placed, _ = block_states(items, stats, 1, max(block or 0, stats.n.bit_length(), -(-stats.n // 2_000)))
    inside = Window.partitionBy("is_heavy", "chunk").orderBy("id").rowsBetween(Window.unboundedPreceding, 0)
    rows = placed.withColumn("rank", (F.col("k0") + F.row_number().over(inside)).cast(UNITS)).withColumn("prefix", (F.col("m0") + F.sum("mass").over(inside)).cast(UNITS))
    return split_and_pack(rows, stats.n, stats.total, packets, block)


def greedy_pass(items: DataFrame, ranges: int, stats: Stats) -> DataFrame:
    """First phase of the greedy build: (kind, id, part, alias): finished buckets and leftovers.

    Every contiguous id range is swept by its own task until one class runs out; what is
    left, with a partly used heavy item at its residual mass, is a leftover.
    """
    rows = classify(items, stats)
    rows = with_block(rows, "id", boundaries(rows, "id", ranges), "r").withColumn("cap", F.lit(Decimal(stats.total)).cast(UNITS))
    t = _kind(items)

    def run(group: pa.Table) -> pa.Table:
        cap = int(group.column("cap")[0].as_py())
        every = sorted((i, int(m)) for i, m in zip(group.column("id").to_pylist(), group.column("mass").to_pylist(), strict=True))
        light, heavy = [x for x in every if x[1] <= cap], [x for x in every if x[1] > cap]
        done, i, j = [], 0, 0
        left = heavy[0][1] if heavy else 0
        while j < len(heavy):
            if left > cap:
                if i == len(light):
                    break
                done.append((light[i][0], light[i][1], heavy[j][0] if light[i][1] < cap else None))
                left -= cap - light[i][1]
                i += 1
            else:
                if j + 1 == len(heavy) and left < cap:
                    break
                done.append((heavy[j][0], left, heavy[j + 1][0] if left < cap else None))
                left = heavy[j + 1][1] - (cap - left) if j + 1 < len(heavy) else 0
                j += 1
        rest = light[i:] + ([(heavy[j][0], left)] if j < len(heavy) else []) + heavy[j + 1 :]
        rows = [(True, *d) for d in done] + [(False, x, m, None) for x, m in rest]
        c = list(zip(*rows, strict=True)) or [[], [], [], []]
        kind = group.column("id").type
        return pa.table({"done": pa.array(c[0], pa.bool_()), "id": pa.array(c[1], kind), "part": pa.array([Decimal(x) for x in c[2]], WIDE), "alias": pa.array(c[3], kind)})

    return rows.groupBy("r").applyInArrow(run, f"done boolean, id {t}, part {UNITS}, alias {t}")


def alias_greedy(items: DataFrame, ranges: int, packets: int | None = None) -> DataFrame:
    """Greedy build: each range packs what it can alone; what is left is ranked over all
    ranges, split and packed.  The leftovers fill whole buckets, as the finished ones do."""
    stats = weight_stats(items)
    cap = F.lit(Decimal(stats.total)).cast(UNITS)
    first = materialise(greedy_pass(items, ranges, stats))
    done, rest = first.where("done").drop("done"), first.where("not done").select("id", F.col("part").alias("mass"), (F.col("part") > cap).alias("is_heavy"))
    n = rest.count()
    left = split_and_pack(rank_masses(rest, blocks_for(n)), n, stats.total, packets or ranges, max(1, n.bit_length()))
    return done.withColumn("cap", cap).unionByName(left)


# ---- persisted form, draws and checks ----------------------------------------------------


def numbered(table: DataFrame, n: int, blocks: int | None = None) -> DataFrame:
    """Adds dense bucket numbers 0..n-1 in id order, unless the build has given them."""
    if "bucket" in table.columns:
        return table
    return block_prefix_sum(table, "id", {"bucket": F.lit(1)}, blocks_for(n, blocks)).withColumn("bucket", (F.col("bucket") - 1).cast("long"))


def draw_requests(table: DataFrame, k: int, n: int, seed: int) -> DataFrame:
    """k requests (draw, bucket, u): a random bucket and a coin, from hash variates."""
    draws = table.sparkSession.range(k).withColumnRenamed("id", "draw")
    bucket = F.least((hash_uniform(seed, F.lit("bucket"), F.col("draw")) * n).cast("long"), F.lit(n - 1))
    return draws.select("draw", bucket.alias("bucket"), hash_uniform(seed, F.lit("coin"), F.col("draw")).alias("u"))


def pick(u: Column, part: Column, cap: Column, own: Column, alias: Column, branchless: bool = False) -> Column:
    """The biased coin: the bucket's own item, or its alias."""
    other = u * cap.cast("double") >= part.cast("double")
    if branchless:
        return F.element_at(F.array(own, F.coalesce(alias, own)), other.cast("int") + 1)
    return F.when(other, F.coalesce(alias, own)).otherwise(own)


def draw_alias(numbered_table: DataFrame, k: int, n: int, seed: int = 7, branchless: bool = False) -> DataFrame:
    """(draw, id): k independent draws; requests of a bounded size are broadcast, others shuffled."""
    asked = draw_requests(numbered_table, k, n, seed)
    joined = numbered_table.join(F.broadcast(asked) if k <= BROADCAST_DRAWS else asked, "bucket")
    return joined.select("draw", pick(F.col("u"), F.col("part"), F.col("cap"), F.col("id"), F.col("alias"), branchless).alias("id"))


def draw_counts(draws: DataFrame) -> DataFrame:
    """(id, k_i): repeats merged by a hash aggregate."""
    return draws.groupBy("id").agg(F.count("*").alias("k_i"))


def mass_check(table: DataFrame, items: DataFrame, stats: Stats) -> DataFrame:
    """(id, mass_ok): whether own parts and alias complements of each item add up to its mass."""
    own = table.select("id", "part").unionByName(table.where("alias is not null").select(F.col("alias").alias("id"), (F.col("cap") - F.col("part")).cast(UNITS).alias("part")))
    total = own.groupBy("id").agg(F.sum("part").alias("mass"))
    return classify(items, stats).select("id", F.col("mass").alias("want")).join(total, "id", "left").select("id", (F.coalesce(F.col("mass"), F.lit(0)) == F.col("want")).alias("mass_ok"))


def two_table_layout(numbered_table: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The layout of one array per field: (bucket, id, part, cap) and (bucket, alias)."""
    return numbered_table.select("bucket", "id", "part", "cap"), numbered_table.select("bucket", "alias")


def draw_two_tables(own: DataFrame, alias: DataFrame, k: int, n: int, seed: int = 7) -> DataFrame:
    """Draws against the two-table layout: two joins instead of one."""
    asked = draw_requests(own, k, n, seed)
    both = asked.join(own, "bucket").join(alias, "bucket")
    return both.select("draw", pick(F.col("u"), F.col("part"), F.col("cap"), F.col("id"), F.col("alias")).alias("id"))
