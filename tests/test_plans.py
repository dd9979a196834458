"""Plans: pruning reaches the scan, no item-size data meets in one task."""

from pyspark.sql import functions as F

from weightdraw.operators import alias as A
from weightdraw.operators import items as I
from weightdraw.operators.prefix import block_prefix_sum, boundaries
from weightdraw.streaming.reservoir import WeightedReservoir, keyed


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_prefix_sum_has_no_single_partition(spark):
    df = spark.range(1000).withColumnRenamed("id", "k")
    out = block_prefix_sum(df, "k", {"run": df.k}, blocks=4)
    assert "SinglePartition" not in plan(out)
    rows = {r.k: int(r.run) for r in out.collect()}
    assert all(rows[k] == k * (k + 1) // 2 for k in rows)


def test_alias_reads_two_columns(spark, tmp_path):
    path = str(tmp_path / "t")
    spark.createDataFrame([(i, float(i + 1), "x") for i in range(50)], "id long, w double, payload string").write.parquet(path)
    items = I.weighted_items(spark.read.parquet(path), "id", "w")
    text = plan(items)
    assert "payload" not in text
    assert A.alias_asof(items, blocks=2).count() == 50


def test_threshold_filters_in_the_scan_stage(spark):
    items = I.weighted_items(spark.createDataFrame([(i, float(i + 1)) for i in range(50)], "id long, w double"), "id", "w")
    text = plan(keyed(items, 7).where("key < 0.01").groupBy("id").count())
    assert text.index("Filter") > text.index("Exchange")  # below it in the tree


def test_reservoir_ignores_batch_boundaries(spark):
    rows = I.weighted_items(spark.createDataFrame([(i, float(1 + i % 5)) for i in range(120)], "id long, w double"), "id", "w").cache()
    found = []
    for cuts in ([0, 120], [0, 30, 35, 120]):
        r = WeightedReservoir(spark, 10, 7)
        for b, (lo, hi) in enumerate(zip(cuts, cuts[1:], strict=False)):
            r.process_batch(rows.where(f"id >= {lo} and id < {hi}"), b)
        r.process_batch(rows.where(f"id >= {cuts[-2]} and id < {cuts[-1]}"), len(cuts) - 2)  # replay
        found.append(sorted(x["id"] for x in r.current().collect()))
    assert found[0] == found[1]


def test_many_chunks_of_neighbours_need_no_cut_points(spark, monkeypatch):
    items = I.weighted_items(spark.range(3, 30_003).select("id", (1 + F.col("id") % 7).cast("double").alias("w")), "id", "w")
    stats = I.weight_stats(items)
    asked = []
    monkeypatch.setattr(A, "boundaries", lambda df, key, blocks: asked.append(blocks) or boundaries(df, key, blocks))
    rows, chunks = A.class_chunks(items, stats, 5)
    assert not asked and chunks == 6_000
    assert {r["n"] for r in rows.groupBy("chunk").agg(F.count("*").alias("n")).collect()} == {5}
    assert A.block_states(items, stats, 3, 5)[1] == A.block_states(items, stats, 3, 500)[1] and asked
