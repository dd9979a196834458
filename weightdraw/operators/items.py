"""Weighted items: a DataFrame with a unique id, a weight and exact integer units.

Weights are kept as integers, ``units = round(w * scale)``, in DECIMAL(38,0), so sums and
splits do not depend on the order of summation and other engines reproduce them.
"""

from __future__ import annotations

from dataclasses import dataclass
from decimal import Decimal

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.variates import hash_uniform

UNITS = "decimal(38,0)"


@dataclass(frozen=True)
class Stats:
    """n items, total and extreme units, number of rejected rows."""

    n: int
    total: int
    least: int
    most: int
    rejected: int = 0

    @property
    def spread(self) -> float:
        return self.most / self.least if self.least else float("nan")

    @property
    def classes(self) -> int:
        """Number of power-of-two classes that the weights may occupy."""
        return (self.most // self.least).bit_length() if self.least else 0


def weighted_items(df: DataFrame, id_col: Column | str, weight: Column | str, scale: int = 1, strict: bool = False) -> DataFrame:
    """(id, w, units) of the rows with a valid weight.

    Weights that are null, NaN, infinite or at most 0, and weights of less than half a
    unit, are dropped; ``strict`` raises instead.  Ids are kept verbatim.
    """
    ident = F.col(id_col) if isinstance(id_col, str) else id_col
    w = (F.col(weight) if isinstance(weight, str) else weight).cast("double")
    rows = df.select(ident.alias("id"), w.alias("w"))
    good = F.col("w").isNotNull() & ~F.isnan("w") & (F.col("w") > 0) & (F.col("w") < float("inf"))
    if strict and (bad := rows.where(~F.coalesce(good, F.lit(False))).count()):
        raise ValueError(f"{bad} rows have no valid weight")
    rows = rows.where(good).withColumn("units", F.round(F.col("w") * scale).cast(UNITS))
    return rows.where("units > 0")


def count_invalid(df: DataFrame, weight: str) -> DataFrame:
    """(n_rows, n_invalid): how many rows the validity rule drops."""
    w = F.col(weight).cast("double")
    good = F.coalesce(~F.isnan(w) & (w > 0) & (w < float("inf")), F.lit(False))
    return df.agg(F.count("*").alias("n_rows"), F.count_if(~good).alias("n_invalid"))


def weight_stats(items: DataFrame) -> Stats:
    """One partial and final aggregate; a single row reaches the driver."""
    r = items.agg(F.count("*").alias("n"), F.sum("units").alias("t"), F.min("units").alias("a"), F.max("units").alias("b")).first()
    return Stats(r.n, int(r.t or 0), int(r.a or 0), int(r.b or 0))


def classify(items: DataFrame, stats: Stats | None = None) -> DataFrame:
    """Adds ``mass`` = n * units and ``is_heavy``: mass above the capacity W (ties are light)."""
    stats = stats or weight_stats(items)
    mass = (F.col("units") * F.lit(stats.n).cast("decimal(18,0)")).cast(UNITS)
    return items.withColumn("mass", mass).withColumn("is_heavy", F.col("mass") > F.lit(Decimal(stats.total)).cast(UNITS))


def unique_ids(items: DataFrame) -> bool:
    """Whether no id occurs twice; samplers need that."""
    return items.groupBy("id").count().where("count > 1").limit(1).count() == 0


def random_shard(items: DataFrame, shards: int, seed: int = 0, portable: bool = False) -> DataFrame:
    """Random allocation of items to workers by a hash of the id (``portable``: the md5 variate)."""
    if portable:
        return items.withColumn("shard", F.least(F.floor(hash_uniform(seed, F.lit("shard"), F.col("id")) * shards), F.lit(shards - 1)).cast("int"))
    return items.withColumn("shard", F.pmod(F.xxhash64(F.lit(seed), F.col("id")), F.lit(shards)).cast("int"))
