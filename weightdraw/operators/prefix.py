"""Distributed prefix sums and as-of lookups without a single-task window.

Rows get a range block from literal boundaries of the order key (collected once from a
small hash-ordered sample, so a retried task sees the same blocks).  Block totals, one
row a block, are scanned on the driver and go back as literals; the running part stays
inside a block.
"""

from __future__ import annotations

import math
from decimal import Decimal
from itertools import accumulate

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.stored import materialise
from .items import UNITS

#: Most rows aimed at per block, rows from which a block is worth a task, blocks up to which that counts.
BLOCK_ROWS, LEAST_ROWS, SPREAD = 500_000, 20_000, 16
#: Sample rows per boundary, most blocks the driver scans.
SAMPLE, MAX_BLOCKS = 32, 100_000


def boundaries(df: DataFrame, key: str, blocks: int) -> list:
    """Up to ``blocks - 1`` literal cut points of the key, from a hash-ordered sample."""
    if blocks <= 1:
        return []
    rows = df.select(key).where(F.col(key).isNotNull()).orderBy(F.xxhash64(key)).limit(blocks * SAMPLE).collect()
    found = sorted(r[0] for r in rows)
    return sorted({found[len(found) * k // blocks] for k in range(1, blocks)}) if found else []


def with_block(df: DataFrame, key: str, cuts: list, name: str = "_block") -> DataFrame:
    """Adds the number of cut points at or below the key; equal keys share a block."""
    if not cuts:
        return df.withColumn(name, F.lit(0))
    kind = df.schema[key].dataType
    array = lambda xs: F.array(*[F.lit(c).cast(kind) for c in xs])
    upto = lambda xs: F.size(F.filter(xs, lambda c: c <= F.col(key)))
    if len(cuts) <= 32:
        return df.withColumn(name, upto(array(cuts)))
    # two levels, so a row meets about 2 sqrt(blocks) cut points and not all of them
    width = math.isqrt(len(cuts))
    parts = [cuts[i : i + width] for i in range(0, len(cuts), width)]
    coarse = upto(array([p[0] for p in parts]))
    fine = F.element_at(F.array(*[array(p) for p in parts]), F.greatest(coarse, F.lit(1)))
    return df.withColumn(name, F.when(coarse == 0, 0).otherwise((coarse - 1) * width + upto(fine)))


def blocks_for(n: int, blocks: int | None = None) -> int:
    return min(MAX_BLOCKS, blocks or max(1, -(-n // BLOCK_ROWS), min(SPREAD, n // LEAST_ROWS)))


def block_prefix_sum(df: DataFrame, key: str, values: dict[str, Column], blocks: int = 8, tie: str | None = None) -> DataFrame:
    """Adds for each (name, value) the inclusive running sum of the value in key order.

    Values are DECIMAL or integer.  Two aggregates' worth of work: block totals (a few
    rows, scanned on the driver), then a running window inside each block.
    """
    cuts = boundaries(df, key, blocks)
    rows = with_block(df, key, cuts)
    for name, value in values.items():
        rows = rows.withColumn(f"_v_{name}", value.cast(UNITS))
    totals = {r["_block"]: r for r in rows.groupBy("_block").agg(*[F.sum(f"_v_{n}").alias(n) for n in values]).collect()}
    order = [F.col(key)] + ([F.col(tie)] if tie else [])
    inside = Window.partitionBy("_block").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    for name in values:
        sums = [int(totals[b][name] or 0) if b in totals else 0 for b in range(len(cuts) + 1)]
        before = [0, *accumulate(sums)][:-1]
        carry = F.element_at(F.array(*[F.lit(Decimal(x)).cast(UNITS) for x in before]), F.col("_block") + 1)
        rows = rows.withColumn(name, (carry + F.sum(f"_v_{name}").over(inside)).cast(UNITS))
    return rows.drop("_block", *[f"_v_{n}" for n in values])


def block_sums(df: DataFrame, key: str, cuts: list, value: str) -> DataFrame:
    """(block, n, total): the summary that the driver scans."""
    return with_block(df, key, cuts, "block").groupBy("block").agg(F.count("*").alias("n"), F.sum(value).alias("total"))


def next_at_or_after(probes: DataFrame, reference: DataFrame, probe_key: str, ref_key: str, payload: list[str], strict: bool, blocks: int = 8) -> DataFrame:
    """For every probe the payload of the first reference row with key > (or >=) the probe's.

    An as-of join forward in key order: union of both sides, first non-null payload after
    the probe inside a range block, and for probes at the end of a block the first
    reference row of a later block, carried by the driver (one row a block).
    """
    reference = materialise(reference.select(F.col(ref_key).alias("_k"), F.struct(*payload).alias("_r")))
    kind = reference.schema["_r"].dataType
    left = probes.select(F.col(probe_key).alias("_k"), F.lit(1 if strict else 0).alias("_side"), F.struct(*[F.col(c) for c in probes.columns]).alias("_p"), F.lit(None).cast(kind).alias("_r"))
    right = reference.select("_k", F.lit(0 if strict else 1).alias("_side"), F.lit(None).cast(left.schema["_p"].dataType).alias("_p"), "_r")
    cuts = boundaries(reference, "_k", blocks)
    both = with_block(left.unionByName(right), "_k", cuts)
    # backwards, because only a growing frame is evaluated in one pass
    after = Window.partitionBy("_block").orderBy(F.desc("_k"), F.desc("_side")).rowsBetween(Window.unboundedPreceding, -1)
    both = both.withColumn("_found", F.last("_r", ignorenulls=True).over(after))
    first = with_block(reference, "_k", cuts).groupBy("_block").agg(F.min(F.struct("_k", "_r")).alias("head"))
    heads = {r["_block"]: r["head"] for r in first.collect()}
    later, carried = None, {}
    for b in range(len(cuts), -1, -1):
        carried[b] = later
        if b in heads:
            later = heads[b]["_r"]
    rows = [(b, later) for b, later in carried.items() if later is not None]
    spark = probes.sparkSession
    table = F.broadcast(spark.createDataFrame(rows, f"_b int, _later {kind.simpleString()}"))
    out = both.where("_p is not null").join(table, F.col("_block") == F.col("_b"), "left")
    out = out.withColumn("_found", F.coalesce("_found", "_later"))
    return out.select("_p.*", *[F.col(f"_found.{c}").alias(f"found_{c}") for c in payload])
