"""Maps of many group counts in one plan equal those made one by one; the schedule equals a walk over clocks."""

import random

import pytest
from pyspark.sql import functions as F

from tilebalance import decomp, threads
from tilebalance.lattice import Domain, lattice

DOM = Domain((32, 16), (2, 2))
COUNTS = (1, 2, 4, 16, 64)


@pytest.fixture(scope="module")
def load(spark):
    tiles = lattice(spark, DOM).withColumn("step", F.explode(F.array(F.lit(0), F.lit(3))))
    return tiles.withColumn("load_u", F.pmod(F.col("tile_id") * 37 + F.col("step") * 11, F.lit(23)) * F.when(F.col("tx") == 3, 40).otherwise(1))


@pytest.mark.parametrize("scheme", ["uniform", "rectilinear", "jagged", "snake", "hilbert", "by_load"])
def test_each_count(spark, load, scheme):
    repair = scheme in ("snake", "hilbert")
    got = {(r.n_pe, r.step, r.tile_id): r.pe for r in decomp.decompose_each(load, DOM, COUNTS, scheme, nonempty=repair).collect()}
    for n in COUNTS:
        own = {(n, r.step, r.tile_id): r.pe for r in decomp.decompose(load, DOM, n, scheme, nonempty=repair).collect()}
        assert own == {k: pe for k, pe in got.items() if k[0] == n}


def test_counts_beyond_the_lattice(load):
    for counts in ((), (0,), (DOM.n_tiles + 1,)):
        with pytest.raises(ValueError):
            decomp.decompose_each(load, DOM, counts, "hilbert")


def test_schedule(spark):
    rng = random.Random(5)
    rows = [(t, [rng.randrange(4) * rng.randrange(30) for _ in range(n)]) for t in (1, 2, 3, 16) for n in (0, 1, 5, 40)]
    want = []
    for t, loads in rows:
        clocks = [0] * t
        for x in loads:
            clocks[clocks.index(min(clocks))] += x
        want.append(max(clocks))
    df = spark.createDataFrame([(i, t, l) for i, (t, l) in enumerate(rows)], "i int, t int, l array<bigint>")
    got = df.select("i", threads.makespan(F.col("l"), F.col("t")).alias("m")).orderBy("i").collect()
    assert [r.m for r in got] == want


def test_steps_need_no_second_scan(spark, capsys):
    from tilebalance.queries.balance import load_of

    load_of(spark, "/root/testdata/sf0.001", "w7").explain("simple")
    assert capsys.readouterr().out.split("== Final Plan ==")[-1].count("FileScan") == 1
