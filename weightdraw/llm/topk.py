"""Exact top-k inner-product search by columnar branch and bound (operator 6).

Vectors become integers, ``floor(256 * x)``.  Queries (a stated set) go out in blocks of
a checked size; candidates stay where they are.  A task turns a run of candidates into
a vertical layout, one array per block of dimensions, and for each query adds up the
inner product block by block.  After a block, what is still missing of a score lies
within ``|rest of q| * |rest of c|`` (the remaining mass), so candidates whose upper
bound is below the k-th best lower bound are compacted away.  The last survivors have
exact integer scores; a window keeps the k best per query of all tasks.

Integer sums are exact in doubles below 2^53; beyond, a run falls back to exact Python
integers.  Bounds carry a relative margin, so rounding never prunes a winner, and only
strictly worse candidates go, so ties reach the final order (score, then smaller id).

Defined results for odd rows: vectors that are null or hold a null, NaN or infinite
component take no part, neither do rows with a null vec_id; vectors of unequal length
are compared as if padded with zeros; rows that share the query's vec_id are its own;
repeated candidate rows count each; a query without candidates has no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import ship

#: Bytes of query vectors sent out at once, candidates in a run, dimensions in a block.
QUERY_BYTES = 16 << 20
RUN = 8192
BLOCK = 16


def _matrix(lists: pa.Array, width: int) -> np.ndarray:
    """floor(256 x) as a [rows, width] array of doubles, zero padded."""
    lists = lists.cast(pa.large_list(pa.float64()))
    flat = np.floor(256 * lists.flatten().to_numpy(zero_copy_only=False))
    size = np.diff(lists.offsets.to_numpy())
    if len(size) and (size == width).all():
        return flat.reshape(-1, width)
    out = np.zeros((len(size), max(width, int(size.max(initial=0)))))
    out[np.arange(out.shape[1])[None, :] < size[:, None]] = flat
    return out


class _Run:
    """Vertical layout of a run of candidates, with the mass that remains after each block."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray, width: int) -> None:
        self.ids, self.rows = ids, rows
        cuts = list(range(0, width, BLOCK))
        self.columns = [np.ascontiguousarray(rows[:, c : c + BLOCK]) for c in cuts]
        mass = np.array([(x * x).sum(axis=1) for x in self.columns])
        self.rest = np.sqrt(np.cumsum(mass[::-1], axis=0)[::-1])
        self.top = float(self.rest[0].max(initial=0.0))

    def best(self, query: np.ndarray, own: int, k: int, floor: float) -> tuple[np.ndarray, np.ndarray]:
        """(ids, scores) of all candidates that may be among the k best."""
        cuts = [query[c : c + BLOCK] for c in range(0, len(query), BLOCK)]
        rest = np.sqrt(np.cumsum([(c * c).sum() for c in cuts][::-1])[::-1])
        if rest[0] * self.top >= 2**52:
            keep = np.flatnonzero(self.ids != own)
            q = [int(x) for x in query]
            score = np.array([sum(a * int(b) for a, b in zip(q, self.rows[i], strict=True)) for i in keep], dtype=object)
            return self.ids[keep], score
        alive = np.flatnonzero(self.ids != own)
        part = np.zeros(len(alive))
        for b, column in enumerate(self.columns):
            part = part + (column if len(alive) == len(column) else column[alive]) @ cuts[b]
            if b + 1 == len(cuts) or len(alive) <= k:
                continue
            slack = rest[b + 1] * self.rest[b + 1][alive] * (1 + 1e-9) + 1e-6
            low = part - slack
            bar = max(floor, np.partition(low, len(low) - k)[len(low) - k])
            stay = part + slack >= bar
            alive, part = alive[stay], part[stay]
        return self.ids[alive], part


def _search(held: object, k: int) -> object:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        query_ids, queries = held.value
        found: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        floor = np.full(len(query_ids), -np.inf)

        def take(batch: pa.Table) -> None:
            ids = batch.column(0).combine_chunks().to_numpy(zero_copy_only=False)
            lists = batch.column(1).combine_chunks()
            rows = _matrix(lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists, queries.shape[1])
            padded = np.pad(queries, ((0, 0), (0, rows.shape[1] - queries.shape[1])))
            part = _Run(ids, rows, rows.shape[1])
            for n, own in enumerate(query_ids):
                i, s = part.best(padded[n], own, k, floor[n])
                if n in found:
                    i, s = np.concatenate([found[n][0], i]), np.concatenate([found[n][1], s])
                if len(i) > k:
                    order = np.lexsort((i, -s))[:k] if s.dtype != object else np.array(sorted(range(len(i)), key=lambda x: (-s[x], i[x]))[:k])
                    i, s = i[order], s[order]
                found[n] = i, s
                if len(i) == k:
                    floor[n] = float(min(s)) - (1e-9 * abs(float(min(s))) if s.dtype == object else 0)

        waiting, rows = [], 0
        for batch in batches:
            waiting.append(batch)
            rows += batch.num_rows
            if rows >= RUN:
                take(pa.Table.from_batches(waiting))
                waiting, rows = [], 0
        if rows:
            take(pa.Table.from_batches(waiting))
        for n, (ids, scores) in found.items():
            if len(ids):
                yield pa.RecordBatch.from_arrays([pa.array([int(query_ids[n])] * len(ids)), pa.array(ids, pa.int64()), pa.array([int(s) for s in scores], pa.int64())], names=["query_id", "vec_id", "score"])

    return run


def exact_top_k(vectors: DataFrame, is_query: Column, k: int = 5) -> DataFrame:
    """query_id, rank, vec_id, score of the k best candidates of every query row."""
    good = ~F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding")).where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & good)
    queries = rows.where(is_query)
    shape = queries.agg(F.count("*").alias("n"), F.coalesce(F.max(F.size("embedding")), F.lit(0)).alias("width")).first()
    blocks = max(1, -(-shape.n * max(1, shape.width) * 8 // QUERY_BYTES))
    found = None
    for b in range(blocks):
        own = queries.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b).dropDuplicates(["vec_id"]).toArrow()
        if own.num_rows:
            lists = own.column(1).combine_chunks()
            matrix = _matrix(lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists, shape.width)
            held = vectors.sparkSession.sparkContext.broadcast((own.column(0).to_numpy(), matrix))
            part = rows.mapInArrow(_search(held, k), "query_id long, vec_id long, score long")
            found = part if found is None else found.unionByName(part)
    if found is None:
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), F.asc("vec_id"))
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


ORACLE = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS e
  FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(list_zip(q.e, c.e), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM scored
)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM ranked WHERE rank <= 5
"""

ship(__name__)
