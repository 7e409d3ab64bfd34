"""Borders between tiles: neighbours, messages, guard cells and particles that cross."""

from __future__ import annotations

from functools import reduce
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .lattice import Domain, lattice, tile_id


def _shifted(tiles: DataFrame, dom: Domain, shift: tuple[int, ...]) -> DataFrame:
    """Tiles with b_tile, the tile at the given offset; wrapped or dropped at the border."""
    named = tiles.withColumn("a_tile", F.col("tile_id"))
    moved = named.withColumns({t: F.col(t) + s for t, s in zip(dom.tcols, shift)})
    if dom.periodic:
        moved = moved.withColumns({t: F.pmod(F.col(t), F.lit(n)) for t, n in zip(dom.tcols, dom.tiles)})
    else:
        for t, n in zip(dom.tcols, dom.tiles):
            moved = moved.where(F.col(t).between(0, n - 1))
    return moved.select("a_tile", tile_id(dom).alias("b_tile"))


def tile_edges(spark, dom: Domain) -> DataFrame:
    """Each shared face once: axis, a_tile, b_tile (the next on that axis).  Pure arithmetic on the lattice, no join."""
    tiles = lattice(spark, dom)
    unit = lambda k: tuple(int(i == k) for i in range(dom.dims))
    return reduce(DataFrame.unionByName, [_shifted(tiles, dom, unit(k)).select(F.lit(k).alias("axis"), "a_tile", "b_tile") for k in range(dom.dims)])


def all_neighbours(spark, dom: Domain) -> DataFrame:
    """Directed pairs over all 3**dims - 1 offsets."""
    tiles = lattice(spark, dom)
    shifts = [s for s in product((-1, 0, 1), repeat=dom.dims) if any(s)]
    return reduce(DataFrame.unionByName, [_shifted(tiles, dom, s) for s in shifts])


def classify_edges(edges: DataFrame, assigned: DataFrame, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Adds the groups of both tiles and whether the border lies between two groups."""
    a = assigned.select(*by, F.col("tile_id").alias("a_tile"), F.col("pe").alias("a_pe"))
    b = assigned.select(*by, F.col("tile_id").alias("b_tile"), F.col("pe").alias("b_pe"))
    return edges.join(a, "a_tile").join(b, [*by, "b_tile"]).withColumn("external", F.col("a_pe") != F.col("b_pe"))


def pe_neighbours(classified: DataFrame, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """by, pe, n_neighbours (groups without external borders are missing)."""
    out = classified.where("external")
    both = out.select(*by, F.col("a_pe").alias("pe"), F.col("b_pe").alias("other")).unionByName(out.select(*by, F.col("b_pe").alias("pe"), F.col("a_pe").alias("other")))
    return both.distinct().groupBy(*by, "pe").agg(F.count("*").alias("n_neighbours"))


def border_messages(classified: DataFrame, grouped: bool, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Messages a step: a buffer for each ordered pair of groups and axis round, or one for each directed external face."""
    ext = classified.where("external")
    both = ext.select(*by, "axis", F.col("a_pe").alias("src"), F.col("b_pe").alias("dst")).unionByName(ext.select(*by, "axis", F.col("b_pe").alias("src"), F.col("a_pe").alias("dst")))
    return (both.distinct() if grouped else both).groupBy(*by).agg(F.count("*").alias("n_messages"))


def corner_messages(spark, dom: Domain, assigned: DataFrame, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Messages of the exchange with all neighbours at once: distinct ordered pairs of groups."""
    pairs = classify_edges(all_neighbours(spark, dom), assigned, by).where("external")
    return pairs.select(*by, "a_pe", "b_pe").distinct().groupBy(*by).agg(F.count("*").alias("n_messages"))


def halo(mesh: DataFrame, dom: Domain, width: int = 1) -> DataFrame:
    """Guard cells: each cell within `width` of a face of its tile, copied to the tile beyond the face: dst_tile, the cell's coordinates, value.  A projection; only border cells are emitted."""
    out = []
    for k, (c, t, side, n) in enumerate(zip(dom.ccols, dom.tcols, dom.tile, dom.tiles)):
        for near, step in ((F.col(c) % side < width, -1), (F.col(c) % side >= side - width, 1)):
            own = mesh.withColumns({x: F.expr(f"cast({y} div {s} as int)") for x, y, s in zip(dom.tcols, dom.ccols, dom.tile)}).where(near).withColumn(t, F.col(t) + step)
            own = own.withColumn(t, F.pmod(F.col(t), F.lit(n))) if dom.periodic else own.where(F.col(t).between(0, n - 1))
            out.append(own.select(tile_id(dom).alias("dst_tile"), F.lit(k).alias("axis"), *dom.ccols, "value"))
    return reduce(DataFrame.unionByName, out)


def two_pass(mesh: DataFrame, dom: Domain, assigned: DataFrame, width: int = 1) -> tuple[DataFrame, DataFrame]:
    """First pass, for all tiles: guard cells between tiles of one group, in place, and the others packed into one buffer (src_pe, dst_pe, axis, cells) for each message."""
    own = halo(mesh, dom, width).withColumns({t: F.expr(f"cast({c} div {n} as int)") for t, c, n in zip(dom.tcols, dom.ccols, dom.tile)}).withColumn("src_tile", tile_id(dom))
    a, b = (assigned.select(F.col("tile_id").alias(f"{x}_tile"), F.col("pe").alias(f"{x}_pe")) for x in ("src", "dst"))
    placed = own.join(a, "src_tile").join(b, "dst_tile")
    row = ["dst_tile", "axis", *dom.ccols, "value"]
    buffers = placed.where("src_pe <> dst_pe").groupBy("src_pe", "dst_pe", "axis").agg(F.collect_list(F.struct("dst_tile", *dom.ccols, "value")).alias("cells"))
    return placed.where("src_pe = dst_pe").select(*row), buffers


def unpack(buffers: DataFrame, dom: Domain, classified: DataFrame) -> DataFrame:
    """Second pass, only for tiles with an external border: their guard cells from the buffers, as halo() has them."""
    ext = classified.where("external")
    waiting = ext.select(F.col("a_tile").alias("dst_tile")).union(ext.select("b_tile")).distinct()
    cells = buffers.select("axis", F.explode("cells").alias("c")).select("c.dst_tile", "axis", *[f"c.{x}" for x in dom.ccols], "c.value")
    return cells.join(waiting, "dst_tile", "left_semi")


def pass_tiles(classified: DataFrame, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """by, external, n_tiles: tiles with a face of that kind on any side."""
    both = classified.select(*by, "external", F.col("a_tile").alias("tile")).unionByName(classified.select(*by, "external", F.col("b_tile").alias("tile")))
    return both.distinct().groupBy(*by, "external").agg(F.count("*").alias("n_tiles"))


def halo_add(spill: DataFrame, dom: Domain) -> DataFrame:
    """Deposits of several tiles on one cell, guard cells' too, added up: cx.., value."""
    return spill.groupBy(*dom.ccols).agg(F.sum("value").alias("value"))


def crossings(moves: DataFrame, dom: Domain, assigned: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Particles that leave their tile, counted by source and destination group.

    moves has both positions (cells cx.., nx..) in one row, so nothing is joined
    to find who moved; several tiles in one step count once.
    """
    before = {f"_a{t}": F.expr(f"cast({c} div {s} as int)") for t, c, s in zip(dom.tcols, dom.ccols, dom.tile)}
    after = {f"_b{t}": F.expr(f"cast(n{c[1:]} div {s} as int)") for t, c, s in zip(dom.tcols, dom.ccols, dom.tile)}
    step, a, b = 1, F.lit(0).cast("bigint"), F.lit(0).cast("bigint")
    for t, n in zip(dom.tcols, dom.tiles):
        a, b, step = a + F.col(f"_a{t}") * step, b + F.col(f"_b{t}") * step, step * n
    left = moves.withColumns({**before, **after}).select(*by, a.alias("a_tile"), b.alias("b_tile")).where("a_tile <> b_tile").groupBy(*by, "a_tile", "b_tile").agg(F.count("*").alias("n"))
    own = assigned.select(*by, "tile_id", "pe")
    src, dst = own.select(*by, F.col("tile_id").alias("a_tile"), F.col("pe").alias("src_pe")), own.select(*by, F.col("tile_id").alias("b_tile"), F.col("pe").alias("dst_pe"))
    return left.join(src, [*by, "a_tile"]).join(dst, [*by, "b_tile"]).groupBy(*by, "src_pe", "dst_pe").agg(F.sum("n").alias("n_part"), F.count("*").alias("n_pairs")).withColumn("remote", F.col("src_pe") != F.col("dst_pe"))


def comm_cost(messages: DataFrame, latency: int, per_cell: int, per_part: int) -> DataFrame:
    """Cost of rows with n_messages, n_cells and n_part: latency counts for each message."""
    return messages.withColumn("cost_u", F.col("n_messages") * latency + F.col("n_cells") * per_cell + F.col("n_part") * per_part)
