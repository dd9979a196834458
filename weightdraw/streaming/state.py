"""Reservoirs as keyed state of a stream, and rows that come too late.

The batched reservoir exchanges only candidates but keeps one threshold on the driver; here
every shard keeps its own k smallest keys as state and no driver value is needed, at the
price of sending every row to its shard.  What a shard takes in is appended to the sink,
so the reservoir at any time is the k smallest keys of the sink.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.window import Window

from ..operators.items import random_shard
from .reservoir import keyed


def taken_in(stream: DataFrame, k: int, shards: int, seed: int = 7, weighted: bool = True) -> DataFrame:
    """(shard, id, key) of every row that enters its shard's reservoir of k, once, in append mode.

    State is k keys a shard.  Rows of a key equal to the threshold are taken in too, so
    ties are left to the reader; null keys never enter.
    """
    kind = stream.schema["id"].dataType.simpleString()
    rows = random_shard(keyed(stream, seed, weighted), shards).where("key is not null").select("shard", "id", "key")

    def step(shard: tuple[int], frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = list(state.get[0]) if state.exists else []
        fresh: list[tuple[float, object]] = []
        for frame in frames:  # never more than k of a batch in hand, besides ties
            if len(held) >= k:
                frame = frame[frame["key"] <= held[-1]]
            held = heapq.nsmallest(k, [*held, *frame["key"].tolist()])
            fresh = [x for x in [*fresh, *zip(frame["key"].tolist(), frame["id"].tolist(), strict=True)] if len(held) < k or x[0] <= held[-1]]
        state.update((held,))
        if fresh:
            yield pd.DataFrame({"shard": shard[0], "id": [i for _, i in fresh], "key": [x for x, _ in fresh]})

    return rows.groupBy("shard").applyInPandasWithState(step, f"shard int, id {kind}, key double", "keys array<double>", "append", GroupStateTimeout.NoTimeout)


def held_of(sink: DataFrame, k: int) -> DataFrame:
    """(id, key): the reservoir, read from what the shards took in."""
    return sink.select("id", "key").distinct().orderBy("key", "id").limit(k)


def late_profile(items: DataFrame, batch: str, ts: str, delay: Column) -> DataFrame:
    """(batch, arrived, late): rows behind the watermark, on a table of arrivals in batches.

    The watermark in a batch is the latest time of all batches before it less ``delay`` (an
    interval), as the streaming engine moves it.  Two aggregates; the running maximum
    in between is over one row a batch.  Rows of a null batch come first; a null time is never late.
    """
    latest = items.groupBy(batch).agg(F.max(ts).alias("_latest"))
    before = Window.orderBy(batch).rowsBetween(Window.unboundedPreceding, -1)
    marks = latest.select(F.col(batch).alias("_b"), (F.max("_latest").over(before) - delay).alias("_mark"))
    late = F.count_if(F.col(ts) < F.col("_mark"))
    return items.join(marks, F.col(batch).eqNullSafe(F.col("_b"))).groupBy(batch).agg(F.count("*").alias("arrived"), late.alias("late"))


def dropped_late(query: StreamingQuery) -> int:
    """Rows (of partial aggregates, where the plan makes some first) that a stream's watermark dropped, by the engine's recent progress."""
    return sum(o["numRowsDroppedByWatermark"] for p in query.recentProgress for o in p["stateOperators"])
