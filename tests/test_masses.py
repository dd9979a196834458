"""Masses beyond 64 bits, and packets that no task holds whole."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from weightdraw.operators import alias as A
from weightdraw.operators import items as I


def test_running_masses_beyond_a_bigint(spark, tmp_path):
    spark.range(41).select(F.col("id").alias("o_orderkey"), F.when(F.col("id") == 40, 4e15).otherwise(1e15).alias("o_totalprice")).write.parquet(str(tmp_path / "orders.parquet"))
    got = {r.id: (r.is_heavy, r["rank"], int(r.prefix)) for r in entry.queries()["prefix_light_heavy"](spark, str(tmp_path)).collect()}
    assert got == {i: (False, i + 1, (i + 1) * 41 * 10**17) for i in range(40)} | {40: (True, 1, 41 * 4 * 10**17)}


@pytest.mark.parametrize("scale", [1, 10**15])
def test_packets_are_swept_in_batches(spark, scale):
    rows = spark.range(900).select("id", (1 + F.pmod(F.col("id") * 37, F.lit(101)) * F.when(F.col("id") % 10 == 0, 40).otherwise(1)).cast("double").alias("w"))
    items = I.weighted_items(rows, "id", "w", scale).cache()
    table = lambda df: sorted((r.id, int(r.part), r.alias) for r in df.collect())
    want = table(A.alias_sequential(items, "sweep"))
    size = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 7)
    try:
        for packets in (1, 5):
            made = A.alias_splitpack(items, packets, block=10)
            assert "FlatMapGroupsInArrow" not in made._jdf.queryExecution().executedPlan().toString()
            assert table(made) == want
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", size)
