"""Selection where the rank is far below what the pivots' sketch resolves."""

import pytest
from pyspark.sql import functions as F

from weightdraw.operators import order as O


@pytest.mark.parametrize("pivots", [2, 8])
@pytest.mark.parametrize("k", [30, 399_980])
def test_small_ranks_of_many_rows_take_few_rounds(spark, tmp_path, pivots, k):
    path = str(tmp_path / "keys")
    spark.range(400_000).select(F.pmod(F.col("id") * 48_271, F.lit(400_009)).cast("double").alias("v")).repartition(4).write.parquet(path)
    rows = spark.read.parquet(path)
    want = sorted(i * 48_271 % 400_009 for i in range(400_000))[k - 1]
    got, rounds = O.select_threshold(rows, "v", k, pivots, finish=10, stored=True)
    assert got == want and rounds <= 8
