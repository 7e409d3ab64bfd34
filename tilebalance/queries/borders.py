"""Borders, messages, guard cells and crossings."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from .. import decomp, exchange, metrics
from ..lattice import Domain, bin_particles, lattice
from ..pic import cell_mesh
from ..views import VIEWS as W
from . import query, twins
from .balance import _NONE, assigned
from .work import _POS, _SMALL, _safe, positions


def _edges_sql(dom: Domain, name: str = "edges") -> str:
    """Pairs of tiles at Manhattan distance one (modulo the size), each face once, from a join of all tiles."""
    parts = []
    for k, t in enumerate(dom.tcols):
        same = " AND ".join(f"a.{o} = b.{o}" for o in dom.tcols if o != t) or "TRUE"
        n = dom.tiles[k]
        step = f"b.{t} = (a.{t} + 1) % {n}" if dom.periodic else f"b.{t} = a.{t} + 1"
        parts.append(f"SELECT {k} AS axis, a.tile_id AS a_tile, b.tile_id AS b_tile FROM one a JOIN one b ON {same} AND {step}")
    return f"one AS (SELECT DISTINCT tile_id, {', '.join(dom.tcols)} FROM lat), {name} AS ({' UNION ALL '.join(parts)})"


for _name, _dom in (("edge_faces_2d", W["w1"].dom), ("edge_faces_3d", W["w2"].dom), ("edge_faces_open", replace(W["w1"].dom, periodic=False))):
    query(_name, twins.with_(twins.lattice(_dom, None), _edges_sql(_dom)) + "SELECT * FROM edges")(lambda s, d, dom=_dom: exchange.tile_edges(s, dom))


def _classified(view: str, scheme: str = "hilbert") -> str:
    return twins.with_(twins.assign(W[view], scheme), _edges_sql(W[view].dom), "cl AS (SELECT a.step, axis, a_tile, b_tile, a.pe AS a_pe, b.pe AS b_pe, a.pe <> b.pe AS external FROM edges JOIN asg a ON a.tile_id = a_tile JOIN asg b ON b.step = a.step AND b.tile_id = b_tile)")


def classified(spark, d, view: str, scheme: str = "hilbert"):
    return exchange.classify_edges(exchange.tile_edges(spark, W[view].dom), assigned(spark, d, view, scheme))


_BOTH = "SELECT step, axis, a_pe AS src, b_pe AS dst FROM cl WHERE external UNION ALL SELECT step, axis, b_pe, a_pe FROM cl WHERE external"
query("edge_external", _classified("w7") + "SELECT step, external, count(*) AS n FROM cl GROUP BY ALL")(lambda s, d: classified(s, d, "w7").groupBy("step", "external").agg(F.count("*").alias("n")))
query("edge_pe_neighbours", _classified("w7") + f"SELECT step, src AS pe, count(DISTINCT dst) AS n_neighbours FROM ({_BOTH}) GROUP BY ALL")(lambda s, d: exchange.pe_neighbours(classified(s, d, "w7")))
query("comm_border_grouped", _classified("w7") + f"SELECT step, count(*) AS n_messages FROM (SELECT DISTINCT * FROM ({_BOTH})) GROUP BY step")(lambda s, d: exchange.border_messages(classified(s, d, "w7"), True))
query("comm_border_ungrouped", _classified("w7") + f"SELECT step, count(*) AS n_messages FROM ({_BOTH}) GROUP BY step")(lambda s, d: exchange.border_messages(classified(s, d, "w7"), False))
query("comm_axis_rounds", _classified("w7") + f"SELECT step, axis, count(*) AS n_messages FROM (SELECT DISTINCT * FROM ({_BOTH})) GROUP BY ALL")(lambda s, d: _rounds(s, d))


def _rounds(spark, d):
    """Messages of each axis round."""
    ext = classified(spark, d, "w7").where("external")
    both = ext.select("step", "axis", F.col("a_pe").alias("src"), F.col("b_pe").alias("dst")).unionByName(ext.select("step", "axis", F.col("b_pe").alias("src"), F.col("a_pe").alias("dst")))
    return both.distinct().groupBy("step", "axis").agg(F.count("*").alias("n_messages"))


query(
    "comm_all_neighbours",
    twins.with_(twins.assign(W["w7"], "hilbert")) + "SELECT step, count(*) AS n_messages FROM (SELECT DISTINCT a.step, a.pe AS s, b.pe AS t FROM asg a JOIN asg b ON a.step = b.step AND a.pe <> b.pe "
    "AND least((a.tx - b.tx + 16) % 16, (b.tx - a.tx + 16) % 16) <= 1 AND least((a.ty - b.ty + 16) % 16, (b.ty - a.ty + 16) % 16) <= 1) GROUP BY step",
)(lambda s, d: exchange.corner_messages(s, W["w7"].dom, assigned(s, d, "w7", "hilbert")))

_MESH = Domain((32, 24), (8, 6))
_CELLS = "m AS (SELECT x AS cx, y AS cy, x * 100 + y AS value FROM generate_series(0, 31) a(x), generate_series(0, 23) b(y))"


def _mesh(spark):
    return cell_mesh(spark, _MESH, F.lit(0)).withColumn("value", F.col("cx") * 100 + F.col("cy"))


_HALO = (
    "SELECT (cx // 8 + 3) % 4 + cy // 6 * 4 AS dst_tile, 0 AS axis, cx, cy, value FROM m WHERE cx % 8 < 1 UNION ALL SELECT (cx // 8 + 1) % 4 + cy // 6 * 4, 0, cx, cy, value FROM m WHERE cx % 8 >= 7 "
    "UNION ALL SELECT cx // 8 + (cy // 6 + 3) % 4 * 4, 1, cx, cy, value FROM m WHERE cy % 6 < 1 UNION ALL SELECT cx // 8 + (cy // 6 + 1) % 4 * 4, 1, cx, cy, value FROM m WHERE cy % 6 >= 5"
)
query("halo_copy", f"WITH {_CELLS} {_HALO}")(lambda s, d: exchange.halo(_mesh(s), _MESH))
query("halo_add", f"WITH {_CELLS}, h AS ({_HALO}) SELECT cx, cy, sum(value) AS value FROM (SELECT cx, cy, value FROM m UNION ALL SELECT cx, cy, value FROM h) GROUP BY ALL")(
    lambda s, d: exchange.halo_add(_mesh(s).unionByName(exchange.halo(_mesh(s), _MESH).select("cx", "cy", "value")), _MESH)
)

_MOVES = f"mv AS (SELECT x // 1000 AS cx, y // 1000 AS cy, (x + vx * 400 + 32000) % 32000 // 1000 AS nx, (y + vy * 400 + 32000) % 32000 // 1000 AS ny FROM ({_POS}))"
_SMALL_ASG = "asg AS (SELECT tx + ty * 4 AS tile_id, tx // 2 * 2 + ty // 2 AS pe FROM generate_series(0, 3) a(tx), generate_series(0, 3) b(ty))"
_CROSS = "cr AS (SELECT cx // 8 + cy // 8 * 4 AS a_tile, nx // 8 + ny // 8 * 4 AS b_tile, count(*) AS n FROM mv GROUP BY ALL), cp AS (SELECT a.pe AS src_pe, b.pe AS dst_pe, n, a_tile, b_tile FROM cr JOIN asg a ON a.tile_id = a_tile JOIN asg b ON b.tile_id = b_tile WHERE a_tile <> b_tile)"


def _crossings(spark, d):
    moves = positions(spark, d).selectExpr("x div 1000 AS cx", "y div 1000 AS cy", "pmod(x + vx * 400, 32000) div 1000 AS nx", "pmod(y + vy * 400, 32000) div 1000 AS ny")
    own = lattice(spark, _SMALL).withColumn("pe", decomp.uniform(_SMALL, (2, 2)))
    return exchange.crossings(moves, _SMALL, own)


query("cross_counts", f"WITH {_MOVES}, {_SMALL_ASG}, {_CROSS} SELECT src_pe <> dst_pe AS remote, sum(n) AS n_part FROM cp GROUP BY 1")(lambda s, d: _crossings(s, d).groupBy("remote").agg(F.sum("n_part").alias("n_part")))
query("cross_packed", f"WITH {_MOVES}, {_SMALL_ASG}, {_CROSS} SELECT src_pe, dst_pe, sum(n) AS n_part, count(*) AS n_pairs FROM cp WHERE src_pe <> dst_pe GROUP BY ALL")(lambda s, d: _crossings(s, d).where("remote").drop("remote"))
_SURF = (
    "SELECT v.pe, coalesce(n_faces, 0) AS n_faces, coalesce(surface_cells, 0) AS surface_cells, volume_cells FROM (SELECT pe, sum(n_cells) AS volume_cells FROM asg WHERE step = 25 GROUP BY pe) v LEFT JOIN "
    "(SELECT pe, count(*) AS n_faces, sum(10) AS surface_cells FROM (SELECT a_pe AS pe FROM cl WHERE external AND step = 25 UNION ALL SELECT b_pe FROM cl WHERE external AND step = 25) GROUP BY pe) f USING (pe)"
)
query("comm_surface_volume", _classified("w7") + _SURF)(lambda s, d: metrics.surface_volume(classified(s, d, "w7").where("step = 25"), assigned(s, d, "w7", "hilbert").where("step = 25"), W["w7"].dom))
query("comm_cost", _classified("w7") + f"SELECT step, n_messages, n_cells, 0 AS n_part, n_messages * 50 + n_cells AS cost_u FROM (SELECT step, count(DISTINCT (axis, src, dst)) AS n_messages, count(*) * 10 AS n_cells FROM ({_BOTH}) GROUP BY step)")(
    lambda s, d: exchange.comm_cost(exchange.border_messages(classified(s, d, "w7"), True).join(exchange.border_messages(classified(s, d, "w7"), False).select("step", (F.col("n_messages") * 10).alias("n_cells")), "step").withColumn("n_part", F.lit(0)), 50, 1, 2)
)
_STATS = ("uniform", "snake", "hilbert")


@query("m_comm_stats", " UNION ALL ".join(f"SELECT '{c}' AS scheme, * FROM ({_classified('w7', c)} SELECT step, count(*) FILTER (external) AS n_faces, (SELECT count(*) FROM (SELECT DISTINCT x.step, x.src, x.dst FROM ({_BOTH}) x) y WHERE y.step = cl.step) AS n_pairs FROM cl GROUP BY step)" for c in _STATS))
def _(spark, d):
    out = None
    for c in _STATS:
        cl = classified(spark, d, "w7", c)
        row = cl.groupBy("step").agg(F.count_if("external").alias("n_faces")).join(exchange.pe_neighbours(cl).groupBy("step").agg(F.sum("n_neighbours").alias("n_pairs")), "step").withColumn("scheme", F.lit(c))
        out = row if out is None else out.unionByName(row)
    return out


@query("m_crossing_fraction", " UNION ALL ".join(f"SELECT {s} AS side, round(CAST(count(*) FILTER (cx // {s} <> nx // {s} OR cy // {s} <> ny // {s}) AS DOUBLE) / count(*), 6) AS fraction FROM (WITH {_MOVES} SELECT * FROM mv)" for s in (8, 16)))
def _(spark, d):
    moves = positions(spark, d).selectExpr("x div 1000 AS cx", "y div 1000 AS cy", "pmod(x + vx * 400, 32000) div 1000 AS nx", "pmod(y + vy * 400, 32000) div 1000 AS ny", "explode(array(8, 16)) AS side")
    return moves.groupBy("side").agg(F.round(F.count_if(F.expr("cx div side <> nx div side or cy div side <> ny div side")) / F.count("*"), 6).alias("fraction"))


@query("edge_components", _NONE)
def _(spark, d):
    """Groups of the Hilbert map that are not one region: none."""
    _safe(spark)
    a = assigned(spark, d, "w7", "hilbert")
    return decomp.components(a, exchange.tile_edges(spark, replace(W["w7"].dom, periodic=False))).agg(F.count_if(F.col("n_regions") != 1).alias("violations"))


@query("cluster_no_sort", _NONE)
def _(spark, d):
    """Tiles that two partitions hold after range partitioning by curve order, without any sort of rows: none."""
    from .. import curves

    v = W["w1"]
    rows = bin_particles(v.particles(spark, d), v.dom).withColumn("curve_idx", curves.hilbert_index(v.dom)).repartitionByRange(8, "curve_idx")
    return rows.withColumn("at", F.spark_partition_id()).groupBy("curve_idx").agg(F.countDistinct("at").alias("n")).agg(F.count_if(F.col("n") > 1).alias("violations"))


@query("exchange_two_pass", _classified("w7") + "SELECT step, external, count(DISTINCT a_tile) AS n_tiles FROM cl GROUP BY ALL")
def _(spark, d):
    """Tiles served in the first pass (internal borders, in place) and those that wait for messages."""
    return classified(spark, d, "w7").groupBy("step", "external").agg(F.countDistinct("a_tile").alias("n_tiles"))


_MESH_ASG = "asg AS (SELECT tx + ty * 4 AS tile_id, tx // 2 * 2 + ty // 2 AS pe FROM generate_series(0, 3) a(tx), generate_series(0, 3) b(ty))"


@query("exchange_passes", f"WITH {_CELLS}, {_MESH_ASG}, h AS ({_HALO}) SELECT CASE WHEN a.pe = b.pe THEN 1 ELSE 2 END AS pass, dst_tile, axis, cx, cy, value FROM h JOIN asg a ON a.tile_id = cx // 8 + cy // 6 * 4 JOIN asg b ON b.tile_id = dst_tile")
def _(spark, d):
    """Guard cells by the pass that delivers them."""
    own = lattice(spark, _MESH).withColumn("pe", decomp.uniform(_MESH, (2, 2)))
    local, buffers = exchange.two_pass(_mesh(spark), _MESH, own)
    far = exchange.unpack(buffers, _MESH, exchange.classify_edges(exchange.tile_edges(spark, _MESH), own, ()))
    return local.withColumn("pass", F.lit(1)).unionByName(far.withColumn("pass", F.lit(2)))


query("exchange_pass_tiles", _classified("w7") + "SELECT step, external, count(DISTINCT tile) AS n_tiles FROM (SELECT step, external, a_tile AS tile FROM cl UNION ALL SELECT step, external, b_tile FROM cl) GROUP BY ALL")(
    lambda s, d: exchange.pass_tiles(classified(s, d, "w7"))
)
