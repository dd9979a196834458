"""Class structure on disk: a draw reads the pages of the cells that it has samples in.

Items lie sorted by cell (a class and a hash chunk of it) in Parquet files whose pages
hold about one cell, so ranges of cells reach the scan as pushed filters and the column
index skips the rest.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.stored import shared_dir
from .classes import sample_weights, split_counts, with_class
from .items import weight_stats

#: Items aimed at per cell, cells of a class at most (one row each reaches the driver), items of a file.
CELL_ROWS, CELLS, FILE_ROWS = 1_000, 4_096, 2_000_000
#: Ranges of cells that are pushed to the scan one by one; beyond, a draw reads most pages anyway.
RANGES = 300


@dataclass
class ClassStore:
    """Items sorted by cell, and a table of the cells' sums."""

    spark: SparkSession
    path: str

    @classmethod
    def build(cls, items: DataFrame, path: str | None = None, cell_rows: int = CELL_ROWS) -> ClassStore:
        """Written once: one scan, one exchange by range of cells."""
        spark = items.sparkSession
        path = path or shared_dir(spark)
        stats = weight_stats(items)
        chunks = max(1, min(CELLS, stats.n // cell_rows))
        cell = F.col("wclass").cast("long") * CELLS + F.pmod(F.xxhash64("id"), F.lit(chunks))
        rows = with_class(items, stats.least).select(cell.alias("cell"), "id", "units")
        files = max(1, -(-stats.n // FILE_ROWS))
        rows.repartitionByRange(files, "cell").sortWithinPartitions("cell", "id").write.option("parquet.page.row.count.limit", cell_rows).parquet(f"{path}/items")
        held = spark.read.parquet(f"{path}/items")
        held.groupBy("cell").agg(F.count("*").alias("n"), F.sum("units").alias("units")).write.parquet(f"{path}/cells")
        return cls(spark, path)

    def plan(self, k: int, seed: int = 7) -> list[tuple[int, int, int]]:
        """(cell, draws, items) of the cells that k draws fall in: trees over classes, then over a class's cells."""
        cells: dict[int, list[tuple[int, int, int]]] = {}
        for r in self.spark.read.parquet(f"{self.path}/cells").collect():
            cells.setdefault(r["cell"] // CELLS, []).append((r["cell"], int(r["units"]), r["n"]))
        top = [sum(u for _, u, _ in cells.get(g, ())) for g in range(max(cells, default=-1) + 1)]
        out = []
        for g, m in enumerate(split_counts(top, k, seed) if top else []):
            own = sorted(cells.get(g, ()))
            for (c, _, n), part in zip(own, split_counts([u for _, u, _ in own], m, seed, f"inner:{g}") if own else [], strict=True):
                if part:
                    out.append((c, part, n))
        return out

    def draw(self, k: int, seed: int = 7, cutoff: int = 128, dedup: bool = True) -> DataFrame:
        """(id, k_i, cell): k draws with replacement."""
        plan = self.plan(k, seed)
        rows = self.spark.read.parquet(f"{self.path}/items")
        kind = rows.schema["id"].dataType.simpleString()
        asked = F.broadcast(self.spark.createDataFrame([(c, m) for c, m, _ in plan] or [(-1, 0)], "cell long, m long"))

        def run(group: pa.Table) -> pa.Table:
            order = group.sort_by("id")
            cell, m = order.column("cell")[0].as_py(), order.column("m")[0].as_py()
            w = order.column("units").cast(pa.float64()).to_numpy()
            rng = np.random.Generator(np.random.Philox(key=[seed, cell]))
            at, times, _ = sample_weights(w, m, rng, cutoff, dedup)
            return pa.table({"id": order.column("id").take(pa.array(at)), "k_i": pa.array(times, pa.int64()), "cell": pa.array([cell] * len(at), pa.int64())})

        spans: list[list[int]] = []
        for c, *_ in plan:
            if spans and spans[-1][1] + 1 == c:
                spans[-1][1] = c
            else:
                spans.append([c, c])
        if len(spans) <= RANGES:
            rows = rows.where(reduce(lambda a, b: a | b, [F.col("cell").between(a, b) for a, b in spans], F.lit(False)))
        return rows.join(asked, "cell").groupBy("cell").applyInArrow(run, f"id {kind}, k_i long, cell long")
