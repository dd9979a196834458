"""Reservoirs over batches: restarts, replays, jumps; the structure on disk; distributed splits."""

from datetime import datetime

import numpy as np
import pytest
from pyspark.sql import functions as F

from weightdraw.functions.measures import measured
from weightdraw.operators import alias, classes, items, subset
from weightdraw.operators.overlay import range_overlay
from weightdraw.operators.prefix import block_prefix_sum, with_block
from weightdraw.operators.store import ClassStore
from weightdraw.sources.tables import read_stream
from weightdraw.streaming import state
from weightdraw.streaming.reservoir import WeightedReservoir, keyed, replay, windowed


def rows_of(spark, n, low=0):
    return items.weighted_items(spark.range(low, low + n).select("id", (1 + F.col("id") % 17).cast("double").alias("w")), "id", "w")


def best(spark, n, k):
    return {r.id for r in keyed(rows_of(spark, n), 7).orderBy("key").limit(k).collect()}


@pytest.mark.parametrize("finish", [0, 100_000])
def test_a_restart_goes_on_from_the_state_on_disk(spark, tmp_path, finish):
    path = str(tmp_path / "state")
    make = lambda: WeightedReservoir(spark, 10, 7, path=path, finish=finish)
    one = make()
    one.process_batch(rows_of(spark, 300), 0)
    two = make()
    assert two.threshold == one.threshold
    two.process_batch(rows_of(spark, 300, 300), 1)
    assert {r.id for r in two.current().collect()} == best(spark, 600, 10)
    three = make()  # the batch was not committed upstream: it comes again after a restart
    three.process_batch(rows_of(spark, 300, 300), 1)
    three.process_batch(rows_of(spark, 300, 600), 2)
    assert {r.id for r in three.current().collect()} == best(spark, 900, 10)


def test_replays_with_and_without_selection(spark):
    rows = rows_of(spark, 900).withColumn("b", (F.col("id") / 200).cast("int"))
    for options in ({}, {"finish": 0}, {"finish": 0, "pivots": 1}, {"mode": "gather"}):
        held = replay(rows, "b", WeightedReservoir(spark, 50, 7, **options))
        assert {r.id for r in held.current().collect()} == best(spark, 900, 50), options
        assert [p["arrived"] for p in held.profile] == [200, 200, 200, 200, 100]


def test_jumps_keep_the_law(spark):
    """A heavy item of half the weight in the second batch is kept about as often as clocks keep it."""
    kept = 0
    for seed in range(12):
        held = WeightedReservoir(spark, 5, seed, mode="jumps")
        held.process_batch(rows_of(spark, 60), 0)
        heavy = spark.createDataFrame([(1000 + i, 400.0 if i == 5 else 1.0) for i in range(40)], "id long, w double")
        held.process_batch(heavy, 1)
        got = held.current().collect()
        assert len({r.id for r in got}) == 5 and all(r.key <= held.threshold for r in got)
        kept += 1005 in {r.id for r in got}
    assert kept >= 10


def test_draws_from_disk_read_what_they_need(spark):
    store = ClassStore.build(rows_of(spark, 40_000), cell_rows=100)
    read = {k: measured(spark, lambda k=k: store.draw(k, 3).count())["rows_read"] for k in (5, 5_000)}
    assert read[5] < 0.5 * read[5_000]
    got = store.draw(500, 3).agg(F.sum("k_i").alias("k")).first()
    assert got.k == 500


def test_block_states_equal_item_prefixes(spark):
    rows = items.weighted_items(spark.range(900).select("id", F.pow(F.lit(2.0), F.col("id") % 9).alias("w")), "id", "w")
    stats = items.weight_stats(rows)
    want = alias.split_states(alias.ranked(rows, stats), stats, [stats.n * k // 4 for k in range(1, 4)])
    assert alias.block_states(rows, stats, 4, 30)[1] == want


@pytest.mark.parametrize("power", [0.0, 1.0, 3.0])
def test_builds_agree_on_skewed_weights(spark, power):
    rows = items.weighted_items(spark.range(1, 701).select("id", F.ceil(1e6 / F.pow("id", F.lit(power))).alias("w")), "id", "w")
    table = lambda df: {(r.id, int(r.part), r.alias) for r in df.collect()}
    want = table(alias.alias_sequential(rows, "sweep"))
    assert table(alias.alias_asof(rows, 5)) == want == table(alias.alias_splitpack(rows, 3)) == table(alias.alias_blockwise(rows, 3))
    stats = items.weight_stats(rows)
    assert alias.mass_check(alias.alias_greedy(rows, 4), rows, stats).where("not mass_ok").count() == 0
    assert [r.bucket for r in alias.alias_asof(rows, 5).orderBy("id").collect()] == list(range(700))


def test_many_cut_points_take_two_levels(spark):
    cuts = list(range(5, 4000, 7))
    got = with_block(spark.range(4100), "id", cuts, "b").collect()
    assert all(r.b == np.searchsorted(cuts, r.id, side="right") for r in got)
    run = block_prefix_sum(spark.range(500), "id", {"s": F.col("id")}, 9).orderBy("id").collect()
    assert [int(r.s) for r in run] == np.cumsum(np.arange(500)).tolist()


def test_walks_of_gaps_in_parts(spark):
    hits = subset.skips(spark, [(0, 20_000, 0.1), (1, 3_000, 1.0)], 7, chunk=1_000)
    got = {r.pclass: (r.n, r.d, r.m) for r in hits.groupBy("pclass").agg(F.count("*").alias("n"), F.countDistinct("pos").alias("d"), F.max("pos").alias("m")).collect()}
    assert got[1] == (3_000, 3_000, 2_999) and got[0][0] == got[0][1] and abs(got[0][0] - 2_000) < 250


def test_uniform_counts_add_up():
    for replace in (True, False):
        assert sum(classes.uniform_counts(15_000, 1_000, 8, 7, replace)) == 1_000
    assert classes.uniform_counts(10, 10, 5, 1, False) == [2, 2, 2, 2, 2]


def test_stateful_shards_keep_what_one_reservoir_keeps(spark, tmp_path):
    """Two runs on one checkpoint: the second goes on from the state of the first."""
    source, log, sink = (str(tmp_path / x) for x in ("in", "log", "out"))
    rows = rows_of(spark, 800).select("id", "w")

    def run():
        found = state.taken_in(read_stream(spark, source, rows.schema), 20, 3)
        found.writeStream.format("parquet").option("checkpointLocation", log).trigger(availableNow=True).start(sink).awaitTermination()
        return spark.read.schema(found.schema).parquet(sink)

    rows.where("id < 500").write.parquet(source)
    assert {r.id for r in state.held_of(run(), 20).collect()} == best(spark, 500, 20)
    rows.where("id >= 500").write.mode("append").parquet(source)
    out = run()
    assert {r.id for r in state.held_of(out, 20).collect()} == best(spark, 800, 20)
    assert out.count() < 400  # not every row is taken in


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    source = str(tmp_path / "in")
    days = lambda *xs: spark.createDataFrame([(d * 100 + i, 1.0, datetime(2024, 1, d, 12)) for d in xs for i in range(4)], "id long, w double, ts timestamp").coalesce(1)
    days(9, 10).write.parquet(source)
    query = windowed(read_stream(spark, source, days(1).schema), "1 day", 3, late="1 day").writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "log"))
    query.trigger(availableNow=True).start().awaitTermination()
    days(3, 11).write.mode("append").parquet(source)
    again = query.trigger(availableNow=True).start()
    again.awaitTermination()
    assert state.dropped_late(again) > 0
    table = spark.createDataFrame([(1, datetime(2024, 1, 10)), (2, datetime(2024, 1, 3)), (2, datetime(2024, 1, 11)), (3, datetime(2024, 1, 10))], "b int, ts timestamp")
    got = state.late_profile(table, "b", "ts", F.make_dt_interval(days=F.lit(1))).orderBy("b").collect()
    assert [tuple(r) for r in got] == [(1, 1, 0), (2, 2, 1), (3, 1, 0)]


@pytest.mark.parametrize("blocks", [1, 4])
def test_overlays_equal_brute_force(spark, blocks):
    rng = np.random.default_rng(5)
    for gaps in (0, 3):
        sides = []
        for n in (90, 40):
            at, rows = 0, []
            for i in range(n):
                lo = at + int(rng.integers(0, gaps + 1))
                at = lo + int(rng.integers(0, 6))
                rows.append((i, lo, at))
            sides.append(rows)
        frames = [spark.createDataFrame([*s, (900, None, 5)], "id long, lo long, hi long") for s in sides]
        got = sorted(tuple(r) for r in range_overlay(*frames, blocks).collect())
        assert got == sorted((a, b, max(l, m), min(h, j)) for a, l, h in sides[0] for b, m, j in sides[1] if max(l, m) < min(h, j))
    assert range_overlay(frames[0].limit(0), frames[1], blocks).count() == 0
