from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from tilebalance import exchange
from tilebalance.lattice import Domain, lattice
from tilebalance.pic import cell_mesh


@pytest.mark.parametrize("periodic", [True, False])
@pytest.mark.parametrize("groups", ["0", "tile_id", "tile_id div 5", "tile_id * 7 % 3"])
def test_both_passes_together_are_the_halo(spark, periodic, groups):
    dom = replace(Domain((32, 24), (8, 6)), periodic=periodic)
    mesh = cell_mesh(spark, dom, F.lit(0)).withColumn("value", F.col("cx") * 100 + F.col("cy"))
    own = lattice(spark, dom).withColumn("pe", F.expr(groups))
    classified = exchange.classify_edges(exchange.tile_edges(spark, dom), own, ())
    local, buffers = exchange.two_pass(mesh, dom, own)
    far = exchange.unpack(buffers, dom, classified)
    rows = lambda df: sorted(map(tuple, df.collect()))
    want = exchange.halo(mesh, dom)
    assert rows(local.unionByName(far)) == rows(want)
    pe = {r.tile_id: r.pe for r in own.collect()}
    assert all((pe[r.cx // 8 + r.cy // 6 * 4] == pe[r.dst_tile]) == here for df, here in ((local, True), (far, False)) for r in df.collect())
    faces = [(r.a_tile, r.b_tile) for r in classified.collect()]
    for r in exchange.pass_tiles(classified, ()).collect():
        assert r.n_tiles == len({t for f in faces if (pe[f[0]] != pe[f[1]]) == r.external for t in f})
