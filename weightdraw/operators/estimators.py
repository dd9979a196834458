"""Estimators from samples, and measures of accuracy."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.variates import exp_key, hash_uniform
from .items import Stats, weight_stats
from .prefix import block_prefix_sum, blocks_for


def estimate_total_with(sample: DataFrame, stats: Stats, f: Column) -> DataFrame:
    """(estimate, std_error) of the total of f from draws with replacement (id, k_i, units): (W / k) sum k_i f / w."""
    y = f.cast("double") / F.col("units").cast("double") * float(stats.total)
    r = sample.select(F.col("k_i"), y.alias("y"))
    mean = F.sum(F.col("k_i") * F.col("y")) / F.sum("k_i")
    var = F.sum(F.col("k_i") * F.col("y") * F.col("y")) / F.sum("k_i") - mean * mean
    return r.agg(mean.alias("estimate"), F.sqrt(F.greatest(var, F.lit(0.0)) / F.sum("k_i")).alias("std_error"))


def estimate_total_poisson(sample: DataFrame, f: Column) -> DataFrame:
    """(estimate) from a subset sample (id, pi): sum of f / pi."""
    return sample.agg(F.round(F.sum(f / F.col("pi")), 4).alias("estimate"))


def estimate_total_without(items: DataFrame, k: int, seed: int) -> DataFrame:
    """(estimate) of the total weight from k clocks: the k+1-st clock is the threshold of inclusion."""
    keys = items.select("w", exp_key(hash_uniform(seed, F.col("id")), F.col("w")).alias("key")).orderBy("key").limit(k + 1)
    t = keys.agg(F.max("key")).first()[0]
    return keys.where(F.col("key") < t).agg(F.round(F.sum(F.col("w") / (1 - F.exp(-F.col("w") * t))), 2).alias("estimate"))


def distinct_estimate(items: DataFrame, ells: list[int]) -> DataFrame:
    """(ell, t, expected): share-weighted light part plus heavy items, beside the exact expectation."""
    total = float(weight_stats(items).total)
    p = F.col("units").cast("double") / total
    agg = items.agg(*[x for e in ells for x in (F.round(F.sum(F.least(F.lit(1.0), e * p)), 4).alias(f"t{e}"), F.round(F.sum(1 - F.exp(e * F.log1p(-p))), 4).alias(f"e{e}"))]).first()
    return items.sparkSession.createDataFrame([(e, agg[f"t{e}"], agg[f"e{e}"]) for e in ells], "ell long, t double, expected double")


def hash_rank(rows: DataFrame, n: int) -> DataFrame:
    """Adds ``rank``: the place of a row's variate ``u``, by block prefix sums."""
    return block_prefix_sum(rows, "u", {"rank": F.lit(1)}, blocks_for(n), tie="id").withColumn("rank", F.col("rank").cast("double"))


def fit_report(draws: DataFrame, items: DataFrame, k: int, cells: int) -> DataFrame:
    """(cells, chi_square, p_bound_ok): draws against weights, items grouped in hash cells."""
    total = float(weight_stats(items).total)
    cell = F.floor(hash_uniform(0, F.lit("cell"), F.col("id")) * cells)
    want = items.groupBy(cell.alias("cell")).agg((F.sum("units").cast("double") / total * k).alias("want"))
    got = draws.groupBy(cell.alias("cell")).agg(F.count("*").alias("got"))
    both = want.join(got, "cell", "left").select("want", F.coalesce("got", F.lit(0)).alias("got"))
    chi = both.agg(F.count("*").alias("cells"), F.round(F.sum(F.pow(F.col("got") - F.col("want"), 2) / F.col("want")), 4).alias("chi_square"))
    return chi.withColumn("fits", F.col("chi_square") < F.col("cells") + 4 * math.sqrt(2.0) * F.sqrt("cells"))
