"""Batched weighted reservoirs, replayed or streamed.

Keys are hashes of item ids, so the reservoir after any batches is the k smallest keys
seen so far, whatever the batch boundaries, and a replayed batch changes nothing.  The
threshold is a literal in each batch's scan; only candidates below it are exchanged.
"""

from __future__ import annotations

import hashlib
import heapq
import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.stored import materialise
from ..functions.variates import exp_key, hash_uniform
from ..operators.order import select_threshold


def keyed(items: DataFrame, seed: int, weighted: bool = True) -> DataFrame:
    """Adds ``key``: the exponential clock of the item, or a plain variate."""
    u = hash_uniform(seed, F.col("id"))
    return items.withColumn("key", exp_key(u, F.col("w")) if weighted else u)


#: Candidates and state rows up to which a batch ends in a plain top-k; k up to which the state may be on the driver.
FINISH, LOCAL = 100_000, 10_000


@dataclass
class WeightedReservoir:
    """State: k rows (id, key, batch), a nullable threshold, and per-batch counters.

    ``mode`` is ``select`` (distributed selection with ``pivots`` per round), ``gather``
    (candidates go to the driver, which keeps a heap: the centralised baseline) or
    ``jumps`` (as ``select``, but each task finds its candidates by exponential jumps over
    the running weight instead of a key for every item).  With a ``path``, the state after
    each batch is a directory there: an object made on an old path goes on from it, and a
    batch that is replayed, before or after a restart, starts from the state before it.
    """

    spark: SparkSession
    k: int
    seed: int = 7
    pivots: int = 8
    mode: str = "select"
    weighted: bool = True
    path: str | None = None
    finish: int = FINISH
    threshold: float | None = None
    profile: list[dict] = field(default_factory=list)
    _state: DataFrame | None = None
    _done: dict = field(default_factory=dict)

    def __post_init__(self) -> None:
        if self.path and (held := self._written()):
            self._load(max(held))

    def _written(self) -> list[int]:
        """Batches whose state is on disk, whole."""
        jvm = self.spark._jvm
        root = jvm.org.apache.hadoop.fs.Path(self.path)
        store = root.getFileSystem(self.spark._jsc.hadoopConfiguration())
        found = [x.getPath().getName() for x in store.listStatus(root)] if store.exists(root) else []
        return [int(f[6:]) for f in found if f.startswith("batch=") and store.exists(jvm.org.apache.hadoop.fs.Path(f"{self.path}/{f}/_SUCCESS"))]

    def _load(self, batch_id: int) -> None:
        self._state = self.spark.read.parquet(f"{self.path}/batch={batch_id}").select("id", "key", "batch")
        r = self._state.agg(F.count("*").alias("n"), F.max("key").alias("t")).first()
        self.threshold = r.t if r.n >= self.k else None

    def _before(self, batch_id: int) -> None:
        """Set the state to the one before a batch that has been seen already."""
        if batch_id in self._done:
            self._state, self.threshold = self._done[batch_id]
        elif self.path and (held := self._written()) and max(held) >= batch_id:
            older = [b for b in held if b < batch_id]
            self._state, self.threshold = None, None
            if older:
                self._load(max(older))
        self.profile = [p for p in self.profile if p["batch"] < batch_id]

    def process_batch(self, items: DataFrame, batch_id: int, arrived: int | None = None) -> None:
        self._before(batch_id)
        self._done[batch_id] = self._state, self.threshold
        for old in [b for b in self._done if b < batch_id - 2]:
            del self._done[old]
        if self.mode == "jumps" and self.threshold is not None:
            fresh = jump_candidates(items, self.threshold, self.seed, batch_id)
        else:
            fresh = keyed(items, self.seed, self.weighted)
            fresh = fresh if self.threshold is None else fresh.where(F.col("key") < self.threshold)
        # the one pass over the batch: candidates are written, all later rounds read them
        fresh = materialise(fresh.select("id", "key", F.lit(batch_id).alias("batch")))
        arrived = items.count() if arrived is None else arrived
        candidates, rounds = fresh.count(), 0
        both = fresh if self._state is None else self._state.unionByName(fresh)
        both = both.groupBy("id").agg(F.min("key").alias("key"), F.min("batch").alias("batch"))
        if self.mode == "gather":
            heap = heapq.nsmallest(self.k, ((r.key, str(r["id"]), r["id"], r.batch) for r in both.collect()))
            kept = self.spark.createDataFrame([(i, k, b) for k, _, i, b in heap], both.schema)
        elif candidates + self.k <= self.finish:  # a top-k per task and of tasks is one job
            kept = both.orderBy("key", "id").limit(self.k)
        else:
            both = materialise(both)
            limit, rounds = select_threshold(both, "key", self.k, self.pivots, stored=True)
            kept = both if limit is None else both.where(F.col("key") <= limit)
        if self.path:
            target = f"{self.path}/batch={batch_id}"
            kept.write.mode("overwrite").parquet(target)
            self._state = self.spark.read.schema(kept.schema).parquet(target)
        elif self.k <= LOCAL:
            rows = kept.collect()  # k rows
            self._state, limit = self.spark.createDataFrame(rows, kept.schema), max((r.key for r in rows), default=None) if len(rows) >= self.k else None
        else:
            self._state = materialise(kept)
        if self.path or self.k > LOCAL:
            r = self._state.agg(F.count("*").alias("n"), F.max("key").alias("t")).first()
            limit = r.t if r.n >= self.k else None
        self.threshold = limit if limit is not None else self.threshold
        self.profile.append({"batch": batch_id, "arrived": arrived, "candidates": candidates, "rounds": rounds, "threshold": self.threshold})

    def current(self) -> DataFrame:
        return self._state.select("id", "key", "batch")


def replay(items: DataFrame, batch: str, reservoir: WeightedReservoir) -> WeightedReservoir:
    """Feed a table batch by batch, in the order of its batch column; the table is split once."""
    items = materialise(items, batch)
    for r in sorted(items.groupBy(batch).count().collect()):
        reservoir.process_batch(items.where(F.col(batch) == r[0]), int(r[0]), r["count"])
    return reservoir


def reservoir_profile(items: DataFrame, batch: str, k: int, seed: int = 7) -> DataFrame:
    """(batch, arrived, candidates): what each batch sends, as one plan over all batches.

    Per batch only its k smallest keys can matter later; their running k-th smallest is
    the threshold of the next batch.
    """
    rows = keyed(items, seed)
    order = Window.partitionBy(batch).orderBy("key", "id")
    top = rows.select(batch, "key", "id").withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= k)
    best: list[float] = []
    limits = []
    for b, keys in sorted((r[0], sorted(r["keys"])) for r in top.groupBy(batch).agg(F.collect_list("key").alias("keys")).collect()):
        limits.append((b, best[k - 1] if len(best) >= k else None))
        best = heapq.nsmallest(k, best + keys)
    t = F.broadcast(items.sparkSession.createDataFrame(limits, f"{batch} {items.schema[batch].dataType.simpleString()}, _t double"))
    return rows.join(t, batch).groupBy(batch).agg(F.count("*").alias("arrived"), F.count_if(F.col("_t").isNull() | (F.col("key") < F.col("_t"))).alias("candidates"))


def jump_batch(weights: np.ndarray, threshold: float, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    """(positions, keys) below the threshold by exponential jumps over the running weight.

    The weight skipped is exponential with the threshold as rate; the item reached gets a
    key from the law truncated to below the threshold; the walk goes on behind it.
    """
    run = np.cumsum(weights)
    at, keys, offset = [], [], 0.0
    while True:
        goal = offset - math.log(1 - rng.random()) / threshold
        i = int(np.searchsorted(run, goal, side="left"))
        if i >= len(weights):
            return np.array(at, np.int64), np.array(keys)
        x = math.exp(-threshold * weights[i])
        at.append(i)
        keys.append(-math.log(x + (1 - rng.random()) * (1 - x)) / weights[i])
        offset = float(run[i])


def jump_candidates(items: DataFrame, threshold: float, seed: int, batch_id: int) -> DataFrame:
    """(id, key) below the threshold, by jumps in every task; variates follow (seed, batch, first id of the rows).

    A task looks at one running sum and draws as many variates as it has candidates.
    """
    kind = items.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                name = f"{seed}:{batch_id}:{b.column(0)[0].as_py()}".encode()
                rng = np.random.Generator(np.random.Philox(key=[seed, int.from_bytes(hashlib.md5(name).digest()[:8], "big")]))  # noqa: S324
                at, keys = jump_batch(b.column(1).to_numpy(zero_copy_only=False).astype(float), threshold, rng)
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at)), pa.array(keys, pa.float64())], names=["id", "key"])

    return items.select("id", "w").mapInArrow(run, f"id {kind}, key double")


def reservoir_jumps(batches: list[list[tuple[object, float]]], k: int, seed: int = 7) -> list[tuple[float, object]]:
    """The jump variant on small lists: (key, id) of the final reservoir; for tests of its law."""
    held: list[tuple[float, object]] = []
    for b, batch in enumerate(batches):
        rng = np.random.Generator(np.random.Philox(key=[seed, b]))
        batch = [x for x in batch if x[1] > 0]
        if len(held) < k:
            new = [(-math.log(1 - rng.random()) / x[1], x[0]) for x in batch]
        else:
            at, keys = jump_batch(np.array([x[1] for x in batch]), held[-1][0], rng)
            new = [(float(v), batch[i][0]) for i, v in zip(at, keys, strict=True)]
        held = heapq.nsmallest(k, held + new)
    return held


def reservoir_sequential(stream: list[tuple[object, float, float]], k: int) -> list[object]:
    """One item at a time, (id, weight, variate): replace the largest key; a test oracle."""
    heap: list[tuple[float, object]] = []
    for ident, w, u in stream:
        key = -math.log(u) / w
        if len(heap) < k:
            heapq.heappush(heap, (-key, ident))
        elif key < -heap[0][0]:
            heapq.heapreplace(heap, (-key, ident))
    return [i for _, i in sorted((-a, b) for a, b in heap)]


def bottom_k(items: DataFrame, by: dict[str, Column], k: int, seed: int = 7) -> DataFrame:
    """Reservoir per group: the ids of the k smallest keys, in order.

    On a table a ranked filter keeps k rows of a group in each task before anything is
    exchanged (the engine's window group limit), so no list is longer than k.  On a
    stream, where ranks are not to be had, it is an aggregate of the group (small groups).
    """
    rows, pair = keyed(items, seed), F.struct("key", "id")
    if items.isStreaming:
        found = rows.groupBy(*[c.alias(n) for n, c in by.items()]).agg(F.slice(F.array_sort(F.collect_list(pair)), 1, k).alias("ids"))
    else:
        rows = rows.select("id", "key", *[c.alias(n) for n, c in by.items()])
        rows = rows.withColumn("_r", F.row_number().over(Window.partitionBy(*by).orderBy("key", "id"))).where(F.col("_r") <= k)
        found = rows.groupBy(*by).agg(F.array_sort(F.collect_list(pair)).alias("ids"))
    return found.withColumn("ids", F.transform("ids", lambda x: x["id"]))


def windowed(stream: DataFrame, length: str, k: int, slide: str | None = None, late: str | None = None, seed: int = 7) -> DataFrame:
    """Event-time windowed reservoirs (id, w, ts): exact per window, with an optional watermark."""
    rows = stream.withWatermark("ts", late) if late else stream
    at = F.window("ts", length, slide) if slide else F.window("ts", length)
    return bottom_k(rows, {"window": at}, k, seed).select(F.col("window.start").alias("start"), "ids")


def session_windows(stream: DataFrame, gap: str, by: str, k: int, seed: int = 7) -> DataFrame:
    """Reservoirs of sessions: bursts of one key separated by a gap."""
    rows = keyed(stream, seed)
    g = rows.groupBy(F.session_window("ts", gap).alias("s"), by)
    return g.agg(F.transform(F.slice(F.array_sort(F.collect_list(F.struct("key", "id"))), 1, k), lambda x: x["id"]).alias("ids")).select(by, F.col("s.start").alias("start"), "ids")


def stream_into(reservoir: WeightedReservoir, stream: DataFrame, checkpoint: str):
    """Structured Streaming: every micro-batch goes through ``process_batch``."""
    writer = stream.writeStream.foreachBatch(lambda df, b: reservoir.process_batch(df, b)).option("checkpointLocation", checkpoint)
    return writer.trigger(availableNow=True).start()
