"""Rejection and compressed tables under heavy items."""

from pyspark.sql import functions as F

from weightdraw.operators import items as I
from weightdraw.operators import tables as T


def items_of(spark, n, heavy):
    rows = spark.range(n).select("id", F.when(F.col("id") == n // 2, float(heavy)).otherwise(1.0).alias("w"))
    return I.weighted_items(rows, "id", "w")


def test_compressed_draw_finds_an_item_of_many_words(spark):
    n, k = 12_000, 300
    words, entries = T.compressed_build(items_of(spark, n, n))
    got = [r.id for r in T.compressed_draw(words, entries, int(entries.agg(F.sum("c")).first()[0]), k).collect()]
    assert len(got) == k and 110 <= got.count(n // 2) <= 190


def test_compressed_draw_beyond_the_last_start(spark):
    n, k = 6_000, 200
    rows = spark.range(n).select("id", F.when(F.col("id") == n - 1, float(n)).otherwise(1.0).alias("w"))
    words, entries = T.compressed_build(I.weighted_items(rows, "id", "w"))
    got = [r.id for r in T.compressed_draw(words, entries, int(entries.agg(F.sum("c")).first()[0]), k).collect()]
    assert len(got) == k and 65 <= got.count(n - 1) <= 135


def test_flat_rejection_fills_every_draw(spark):
    got = T.draw_rejection_flat(items_of(spark, 50, 500), 200).collect()
    assert sorted(r.draw for r in got) == list(range(200))
    assert max(r.tries for r in got) > T.TRIES and sum(r.id == 25 for r in got) > 160
