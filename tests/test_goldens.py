"""Hand-computed cases, degenerate inputs, the method's claims on the stand-in workloads, and plans."""

import pytest
from pyspark.sql import functions as F

from tilebalance import curves, cuts, decomp, exchange, metrics, pic, threads
from tilebalance.lattice import Domain, lattice
from tilebalance.load import load_array
from tilebalance.views import VIEWS as W

SF = "/root/testdata/sf0.01"


def line(spark, loads):
    return spark.createDataFrame([(0, i, i, x, x, 1) for i, x in enumerate(loads)], "step int, tile_id bigint, curve_idx bigint, load_u bigint, n_part bigint, n_cells bigint")


def groups(df):
    return [r.pe for r in df.orderBy("curve_idx").collect()]


def test_prefix_greedy_minimax(spark):
    own = line(spark, [4, 1, 1, 6, 2, 2])
    assert groups(cuts.cut_prefix(own, 2)) == [0, 0, 0, 1, 1, 1]
    assert groups(cuts.cut_greedy(own, 2)) == [0, 0, 0, 1, 1, 1]
    assert metrics.imbalance(cuts.cut_prefix(own, 2), 2).first().imbalance == 1.25
    assert cuts.minimax(own, 2).first().bottleneck_u == 10


def test_nonempty_repair(spark):
    own = line(spark, [1, 9, 1, 1])
    cut = cuts.cut_prefix(own, 4)
    assert groups(cut) == [0, 1, 3, 3]
    fixed = cuts.ensure_nonempty(own, cut, 4)
    assert groups(fixed) == [0, 1, 2, 3]
    assert metrics.imbalance(fixed, 4).first().imbalance == 3.0 and threads.alpha(own, 4).first().alpha == 3.0
    with pytest.raises(Exception, match="more groups than tiles"):
        cuts.ensure_nonempty(own, cuts.cut_prefix(own, 5), 5).collect()


def test_no_load_is_cut_by_count(spark):
    assert groups(cuts.cut_prefix(line(spark, [0] * 6), 3)) == [0, 0, 1, 1, 2, 2]


def walk(spark, tiles, kind):
    dom = Domain(tiles, (1,) * len(tiles), order=0)
    rows = lattice(spark, dom).withColumn("i", curves.INDEX[kind](dom)).orderBy("i").collect()
    assert [r.i for r in rows] == list(range(dom.n_tiles))
    return ["".join(str(r[t]) for t in dom.tcols) for r in rows]


def test_walks(spark):
    assert walk(spark, (3, 2), "snake") == "00 10 20 21 11 01".split()
    assert walk(spark, (2, 2, 2), "snake") == "000 100 110 010 011 111 101 001".split()
    assert walk(spark, (4, 4), "hilbert") == "00 10 11 01 02 03 13 12 22 23 33 32 31 21 20 30".split()
    assert walk(spark, (4, 2), "hilbert") == "00 01 11 10 20 21 31 30".split()
    assert walk(spark, (1, 1), "hilbert") == ["00"] and walk(spark, (5,), "hilbert") == list("01234")
    with pytest.raises(curves.CurveShapeError):
        walk(spark, (12, 12), "hilbert")
    assert len(walk(spark, (12, 12), "snake")) == 144


@pytest.mark.parametrize("loads,t,heavy,hybrid,light,all_", [((10, 1, 1, 1, 1, 2), 4, 1, 5.5, 10, 4), ((1, 5), 4, 2, 1.5, 5, 1.5), ((2, 2, 2, 2), 4, 4, 2, 2, 2), ((5, 1, 1, 3), 2, 1, 6.5, 5, 5)])
def test_heavy_and_light(spark, loads, t, heavy, hybrid, light, all_):
    own = line(spark, loads).withColumn("pe", F.lit(0))
    rows = {m: threads.pe_time(own, t, m).first() for m in ("hybrid", "light_only", "heavy_only")}
    assert rows["hybrid"].n_heavy == heavy
    assert [rows[m].time_t / t for m in ("hybrid", "light_only", "heavy_only")] == [hybrid, light, all_]


def test_task_threads_round_half_up(spark):
    own = line(spark, [10, 1, 1, 1, 1, 2]).withColumn("pe", F.lit(0))
    assert [r.slots for r in threads.task_threads(own, 4).orderBy("curve_idx").collect()] == [3, 1, 1, 1, 1, 1]
    assert threads.task_time(own, 4).first().makespan == pytest.approx(1 + 10 / 3)  # after one unit three threads are free; the two-unit tile has the fourth


def test_weights_at_the_centre():
    from pyspark.sql import SparkSession

    spark = SparkSession.getActiveSession()
    row = spark.range(1).select(*[w.alias(f"w{k + 1}") for k, w in pic.shape_weights(F.lit(0.0), 2)]).first()
    assert tuple(row) == (0.125, 0.75, 0.125)


def test_jagged_by_hand(spark):
    dom = Domain((4, 4), (1, 1), order=0)
    rows = [(0, x + 4 * y, x, y, 0, 1, 1 if x in (0, 3) else 0) for x in range(4) for y in range(4)]
    load = spark.createDataFrame(rows, "step int, tile_id bigint, tx int, ty int, n_part bigint, n_cells bigint, load_u bigint")
    got = decomp.decompose(load, dom, 4, "jagged", (2, 2))
    assert {r.tx: r.s for r in got.groupBy("tx").agg(F.min(F.floor(F.col("pe") / 2)).alias("s")).collect()} == {0: 0, 1: 1, 2: 1, 3: 1}


def test_faces(spark):
    for periodic, faces, external in ((False, 24, 8), (True, 32, 16)):
        dom = Domain((4, 4), (1, 1), periodic, 0)
        edges = exchange.tile_edges(spark, dom)
        own = lattice(spark, dom).withColumn("pe", decomp.uniform(dom, (2, 2))).withColumn("step", F.lit(0))
        assert edges.count() == faces
        assert exchange.classify_edges(edges, own).where("external").count() == external


def test_domain_errors():
    with pytest.raises(ValueError):
        Domain((16, 16), (4, 4)).validate()
    with pytest.raises(ValueError):
        Domain((16, 16), (5, 5)).validate()
    assert Domain((20, 20), (5, 5)).validate().n_tiles == 16
    assert decomp.factors(32, (32, 16)) == (8, 4) and decomp.factors(8, (4, 4, 4)) == (2, 2, 2) and decomp.factors(7, (4, 4)) in ((1, 7), (7, 1))


def test_degenerate(spark):
    dom = Domain((16, 16), (8, 8), order=0)
    none = load_array(spark.createDataFrame([(0, 3, 3)], "step int, cx bigint, cy bigint"), dom, (0, 1))
    for scheme in ("uniform", "rectilinear", "jagged", "snake", "hilbert", "by_load", "greedy_hilbert"):
        for n in (1, 4):
            got = decomp.decompose(none, dom, n, scheme)
            assert got.count() == 4 and got.where(~F.col("pe").between(0, n - 1)).count() == 0
    with pytest.raises(ValueError):
        decomp.decompose(none, dom, 5, "hilbert")
    assert threads.classify(decomp.decompose(none, dom, 4, "uniform"), 1).where("is_heavy").count() == 4


def peaks(spark, view, schemes):
    v = W[view]
    load = load_array(v.particles(spark, SF), v.dom, v.weight).cache()
    return {c: {r.step: r.imbalance for r in metrics.imbalance(decomp.decompose(load, v.dom, v.n_pe, c, v.grid), v.n_pe).collect()} for c in schemes}


def test_reference_values_of_the_disc_and_stripe(spark):
    got = peaks(spark, "w7", ("uniform", "rectilinear", "jagged", "snake", "hilbert"))
    want = {"uniform": (2.4467, 2.4467, 2.0556), "rectilinear": (1.5946, 1.6651, 1.1865), "jagged": (1.2931, 1.3953, 1.1865), "snake": (1.2931, 1.2713, 1.0502), "hilbert": (1.2931, 1.2946, 1.0547)}
    assert {c: tuple(round(got[c][s], 4) for s in (14, 25, 50)) for c in got} == want
    stripe = peaks(spark, "w5", ("uniform", "jagged", "snake", "hilbert"))
    assert {c: round(x[0], 4) for c, x in stripe.items()} == {"uniform": 1.6902, "jagged": 1.0716, "snake": 1.0009, "hilbert": 1.0072}


def test_concentration_of_the_ball(spark):
    v = W["w6"]
    load = load_array(v.particles(spark, SF), v.dom, v.weight)
    assert {r.step: r.n_tiles for r in metrics.concentration(load).collect()} == {14: 11, 25: 49, 50: 355}


def test_plans(spark):
    v = W["w7"]
    plan = decomp.decompose(load_array(v.particles(spark, SF), v.dom, v.weight), v.dom, v.n_pe, "hilbert")._jdf.queryExecution().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan
    assert "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint>" in plan


def test_same_result_under_other_partitioning(spark):
    v = W["w9"]
    out = []
    for n in ("1", "7"):
        spark.conf.set("spark.sql.shuffle.partitions", n)
        rows = v.particles(spark, SF).repartition(int(n) + 2)
        out.append(sorted(map(tuple, decomp.decompose(load_array(rows, v.dom, v.weight), v.dom, 32, "hilbert").select("step", "tile_id", "pe").collect())))
    spark.conf.set("spark.sql.shuffle.partitions", "4")
    assert out[0] == out[1]


def test_sql_text_gives_the_same_load(spark):
    from tilebalance.queries import load_all

    v = W["w7"]
    own = load_array(v.particles(spark, SF), v.dom, v.weight).where("step = 50")
    assert sorted((r.tx, r.ty, r.load_u) for r in own.collect()) == sorted((r.tx, r.ty, r.load_u) for r in load_all()["op_sql_surface"][0](spark, SF).collect())
