"""Rows of heavy tiles over all slots, light tiles packed: balance, wholeness, the schedule's times."""

from pyspark.sql import functions as F

from tilebalance import cuts, threads


def tiles(spark, loads, n_pe):
    rows = [(0, k, k, x, x, 1) for k, x in enumerate(loads)]
    df = spark.createDataFrame(rows, "step int, tile_id bigint, curve_idx bigint, load_u bigint, n_part bigint, n_cells bigint")
    return cuts.cut_prefix(df, n_pe)


def test_no_partition_exceeds_mean_and_largest_light_tile(spark):
    loads, t = [1000, 3, 40, 7, 7, 60, 5, 90, 8, 2, 500, 30, 20, 11, 13, 17], 4
    assigned = tiles(spark, loads, 2)
    plan = threads.slot_plan(assigned, t)
    own = {r.tile_id: r for r in plan.collect()}
    assert len(own) == len(loads) and all((r.slot is None) == r.is_heavy for r in own.values()) and any(r.is_heavy for r in own.values())
    rows = spark.createDataFrame([(0, k, 5) for k, x in enumerate(loads) for _ in range(x)], "step int, tile_id bigint, same int").repartition(3)
    placed = threads.place_hybrid(rows, plan, 2, t)
    got = {r.part: r.n for r in placed.groupBy("part").agg(F.count("*").alias("n")).collect()}
    assert sum(got.values()) == sum(loads)
    for pe in range(2):
        mine = [r for r in own.values() if r.pe == pe]
        mean, light = sum(r.load_u for r in mine) / t, max([r.load_u for r in mine if not r.is_heavy], default=0)
        heavy = sum(r.is_heavy for r in mine)
        assert max(got.get(pe * t + k, 0) for k in range(t)) <= mean + light + 3 * (heavy + 1)
    ids = placed.select(F.spark_partition_id().alias("p"), "part").distinct().collect()
    assert all(r.p == r.part for r in ids)


def test_sums_of_private_copies(spark):
    assigned = tiles(spark, [50, 1, 2, 3, 9, 1], 2)
    rows = spark.createDataFrame([(0, k, i % 3) for k, x in enumerate([50, 1, 2, 3, 9, 1]) for i in range(x)], "step int, tile_id bigint, c int")
    placed = threads.place_hybrid(rows, threads.slot_plan(assigned, 4), 2, 4)
    got = sorted(tuple(r) for r in threads.private_sums(placed, ["tile_id", "c"], {"n": F.lit(1)}).collect())
    assert got == sorted(tuple(r) for r in rows.groupBy("tile_id", "c").count().collect())


def test_plan_time_equals_schedule(spark):
    assigned = tiles(spark, [10, 1, 1, 1, 1, 2, 9, 4, 4, 3], 2)
    want = {r.pe: (r.n_heavy, r.time_t) for r in threads.pe_time(assigned, 4).collect()}
    assert {r.pe: (r.n_heavy, r.time_t) for r in threads.plan_time(threads.slot_plan(assigned, 4), 4).collect()} == want


def test_first_indices_with_empty_groups(spark):
    df = spark.createDataFrame([(0, p) for p in [1, 1, 3]] + [(1, 0)], "step int, pe int")
    got = {r.step: (r.cuts, r.m) for r in cuts.first_indices(df, 5).collect()}
    assert got == {0: ([0, 0, 2, 2, 3], 3), 1: ([0, 1, 1, 1, 1], 1)}
