"""Overlay of two sets of intervals on one line, as one pass in position order."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.stored import materialise
from .prefix import boundaries, with_block


def range_overlay(left: DataFrame, right: DataFrame, blocks: int = 8) -> DataFrame:
    """(left, right, lo, hi): the pieces that an interval of each side shares.

    Both sides are (id, lo, hi), half open; intervals of one side do not overlap, empty
    ones and those with a null end take no part.  A piece begins where an interval
    of either side begins, so there are fewer pieces than intervals.  Range blocks are
    passed independently; the last interval of either side that begins before a block
    is carried to it by the driver (one row a block).
    """
    side = lambda df, own, other: df.where("lo < hi").select(F.col("lo").alias("_k"), F.struct("id", "hi").alias(own), F.lit(None).alias(other))
    both = materialise(side(left, "_l", "_r").unionByName(side(right, "_r", "_l")).select("_k", "_l", "_r"))
    cuts = boundaries(both, "_k", blocks)
    rows = with_block(both, "_k", cuts)
    last = {r["_block"]: r for r in rows.groupBy("_block").agg(*[F.max_by(c, F.when(F.col(c).isNotNull(), F.col("_k"))).alias(c) for c in ("_l", "_r")]).collect()}
    carried, state = [], (None, None)
    for b in range(len(cuts) + 1):
        carried.append((b, *state))
        if b in last:
            state = tuple(last[b][c] if last[b][c] is not None else s for c, s in zip(("_l", "_r"), state, strict=True))
    kinds = {c: both.schema[c].dataType.simpleString() for c in ("_l", "_r")}
    before = F.broadcast(left.sparkSession.createDataFrame(carried, f"_b int, _cl {kinds['_l']}, _cr {kinds['_r']}"))
    # where both sides begin at one point, the first of the two rows still sees an interval that ends there
    upto = Window.partitionBy("_block").orderBy("_k", F.col("_l").isNull()).rowsBetween(Window.unboundedPreceding, 0)
    pieces = rows.select("_k", "_block", *[F.last(c, ignorenulls=True).over(upto).alias(c) for c in ("_l", "_r")]).join(before, F.col("_block") == F.col("_b"))
    pieces = pieces.select("_k", F.coalesce("_l", "_cl").alias("_l"), F.coalesce("_r", "_cr").alias("_r"))
    pieces = pieces.select(F.col("_l.id").alias("left"), F.col("_r.id").alias("right"), F.col("_k").alias("lo"), F.least("_l.hi", "_r.hi").alias("hi"))
    return pieces.where("left is not null and right is not null and lo < hi")
