"""Geometry, load, curves, cuts, decompositions, rebalancing and their measures."""

from __future__ import annotations

from dataclasses import replace
from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import curves, cuts, decomp, load as loads, metrics, rebalance
from ..lattice import Domain, apply_boundary, bin_particles, lattice, with_tile_side
from ..views import VIEWS, View
from . import query, twins

W = VIEWS


def load_of(spark: SparkSession, d: str, view: str, weight=None) -> DataFrame:
    v = W[view]
    return loads.load_array(v.particles(spark, d), v.dom, weight or v.weight, steps=v.times(spark))


def assigned(spark: SparkSession, d: str, view: str, scheme: str, n_pe: int | None = None, grid=None, **options) -> DataFrame:
    v = W[view]
    return decomp.decompose(load_of(spark, d, view), v.dom, n_pe or v.n_pe, scheme, grid or v.grid, **options)


# Geometry.
def _binned(view: str):
    v = W[view]
    cols = [*v.dom.tcols, "tile_id"]
    ident, m = [], 1
    for c, s, n in zip(v.dom.ccols, v.dom.tile, v.dom.tiles):
        ident.append(f"{c} // {s} * {m}")
        m *= n
    sql = twins.with_(twins.particles(v)) + f"SELECT step, species, {', '.join(f'{c} // {s} AS {t}' for t, c, s in zip(v.dom.tcols, v.dom.ccols, v.dom.tile))}, {' + '.join(ident)} AS tile_id, count(*) AS n FROM p GROUP BY ALL"
    return (lambda s, d: bin_particles(v.particles(s, d), v.dom).groupBy("step", "species", *cols).agg(F.count("*").alias("n"))), sql


for _name, _view in (("geom_bin_2d", "w1"), ("geom_bin_3d", "w2"), ("geom_noncubic", "w10")):
    _f, _sql = _binned(_view)
    query(_name, _sql)(_f)

_WRAP = {"wrap": "((cy - 40) % 128 + 128) % 128", "clamp": "greatest(0, least(127, cy - 40))", "drop": "cy - 40"}
for _mode, _view, _name in (("wrap", "w5", "geom_wrap"), ("clamp", "w9", "geom_clamp"), ("drop", "w9", "geom_drop")):

    @query(_name, twins.with_(twins.particles(W[_view])) + f"SELECT step, cx, {_WRAP[_mode]} AS cy, count(*) AS n FROM p {'WHERE cy - 40 BETWEEN 0 AND 127' if _mode == 'drop' else ''} GROUP BY ALL")
    def _(spark, d, view=_view, mode=_mode):
        moved = W[view].particles(spark, d).withColumn("cy", F.col("cy") - 40)
        return apply_boundary(moved, W[view].dom, mode).groupBy("step", "cx", "cy").agg(F.count("*").alias("n"))


for _name, _view in (("geom_lattice_2d", "w1"), ("geom_lattice_3d", "w6")):
    query(_name, twins.with_(twins.lattice(W[_view].dom, None)) + f"SELECT *, CAST({W[_view].dom.cells_per_tile} AS BIGINT) AS n_cells FROM lat")(lambda s, d, v=_view: lattice(s, W[v].dom))

_SIDES = [(256, 8), (256, 16), (256, 32), (256, 64), (64, 8), (64, 16), (64, 32), (32, 8), (32, 16), (20, 5), (20, 10), (20, 20)]


def _warm_sql(cells: int) -> str:
    return f"SELECT l_partkey * {cells} // (SELECT count(*) FROM part) AS cx, l_orderkey * {cells} // (SELECT count(*) FROM orders) AS cy FROM lineitem"


@query("geom_sides", " UNION ALL ".join(f"SELECT {c} AS cells, {s} AS side, count(*) AS used, max(n) AS fullest FROM (SELECT cx // {s}, cy // {s}, count(*) AS n FROM ({_warm_sql(c)}) GROUP BY 1, 2)" for c, s in _SIDES))
def _(spark, d):
    from ..views import _warm

    out = None
    for c, s in _SIDES:
        v = _warm(c, c, 1, (1, 1))
        tiles = bin_particles(v.particles(spark, d), with_tile_side(v.dom, s)).groupBy("tile_id").agg(F.count("*").alias("n"))
        row = tiles.agg(F.count("*").alias("used"), F.max("n").alias("fullest")).select(F.lit(c).alias("cells"), F.lit(s).alias("side"), "used", "fullest")
        out = row if out is None else out.unionByName(row)
    return out


# Load.
for _view in ("w1", "w2", "w6", "w9"):
    query(f"load_{_view}", twins.with_(twins.load(W[_view])) + "SELECT * FROM load")(lambda s, d, v=_view: load_of(s, d, v))


@query("load_c_sweep", " UNION ALL ".join(f"SELECT * FROM ({twins.with_(twins.load(W['w7'], w))} SELECT step, {w[0]} AS num, {w[1]} AS den, sum(load_u) AS total_u, max(load_u) AS max_u FROM load GROUP BY step)" for w in ((1, 2), (1, 1), (2, 1))))
def _(spark, d):
    parts = [load_of(spark, d, "w7", w).groupBy("step").agg(F.sum("load_u").alias("total_u"), F.max("load_u").alias("max_u")).withColumns({"num": F.lit(w[0]), "den": F.lit(w[1])}) for w in ((1, 2), (1, 1), (2, 1))]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


query("load_formula", twins.with_(twins.load(W["w7"])) + "SELECT step, tile_id, 3 * n_part + n_cells * 7 AS load_u FROM load")(
    lambda s, d: loads.load_array(W["w7"].particles(s, d), W["w7"].dom, formula=F.col("n_part") * 3 + F.col("n_cells") * 7).select("step", "tile_id", "load_u")
)


def doc_load(spark: SparkSession, d: str, table: str = "documents", key: str = "doc_id", size: str = "n_chars", group: int = 8) -> DataFrame:
    """Text as particles: tiles of `group` neighbouring ids, load = characters."""
    rows = spark.read.parquet(f"{d}/{table}.parquet").selectExpr(f"{key} div {group} AS tile_id", f"cast({size} as bigint) AS n")
    return rows.groupBy("tile_id").agg(F.count("*").alias("n_part"), F.sum("n").alias("load_u")).withColumns({"step": F.lit(0), "n_cells": F.lit(0).cast("bigint"), "curve_idx": F.col("tile_id")})


DOCS = "load AS (SELECT 0 AS step, doc_id // 8 AS tile_id, count(*) AS n_part, CAST(sum(n_chars) AS BIGINT) AS load_u, doc_id // 8 AS curve_idx FROM documents GROUP BY ALL)"
query("load_weighted_docs", twins.with_(DOCS) + "SELECT tile_id, n_part, load_u FROM load")(lambda s, d: doc_load(s, d).select("tile_id", "n_part", "load_u"))
query("load_ideal", twins.with_(twins.load(W["w7"])) + "SELECT step, sum(load_u) AS total_u, CAST(sum(load_u) AS DOUBLE) / 16 AS ideal FROM load GROUP BY step")(lambda s, d: loads.ideal_load(load_of(s, d, "w7"), 16))
query("load_density_species", twins.with_(twins.particles(W["w9"])) + "SELECT step, species, cx // 8 + cy // 8 * 32 AS tile_id, count(*) AS n_part FROM p GROUP BY ALL")(lambda s, d: loads.density(W["w9"].particles(s, d), W["w9"].dom))
query("load_project_axis", twins.with_(twins.load(W["w7"])) + "SELECT step, tx, sum(load_u) AS load_u FROM load GROUP BY ALL")(lambda s, d: loads.project(load_of(s, d, "w7"), "x"))
_CELLS = {k: replace(W[k], dom=Domain(W[k].dom.cells, (1, 1), order=0)) for k in ("w5",)}
query("load_cells", twins.with_(twins.load(_CELLS["w5"])) + "SELECT * FROM load WHERE n_part > 0")(lambda s, d: loads.load_array(_CELLS["w5"].particles(s, d), _CELLS["w5"].dom).where("n_part > 0"))


# Curves.
_LONG2, _LONG3, _CUBE = Domain((64, 16), (1, 1), order=0), Domain((4, 8, 8), (1, 1, 1), order=0), Domain((8, 8, 8), (1, 1, 1), order=0)
_SQUARE = Domain((16, 16), (1, 1), order=0)


def _curve(dom: Domain, kind: str):
    return lambda s, d: lattice(s, dom).select(*dom.tcols, curves.INDEX[kind](dom).alias("curve_idx"))


query("curve_row", twins.with_(twins.lattice(_SQUARE, None)) + "SELECT tx, ty, tile_id AS curve_idx FROM lat")(_curve(_SQUARE, "row_major"))
for _name, _dom, _kind in (("curve_snake_2d", Domain((12, 7), (1, 1), order=0), "snake"), ("curve_snake_3d", Domain((5, 4, 3), (1, 1, 1), order=0), "snake"), ("curve_hilbert_2d", _SQUARE, "hilbert"), ("curve_hilbert_3d", _CUBE, "hilbert"), ("curve_hilbert_stretched_2d", _LONG2, "hilbert")):
    query(_name, twins.with_(twins.curve(_dom, _kind)) + "SELECT * FROM cur")(_curve(_dom, _kind))
query("curve_hilbert_stretched_2d_tall", twins.with_(twins.curve(Domain((8, 32), (1, 1), order=0), "hilbert")) + "SELECT * FROM cur")(_curve(Domain((8, 32), (1, 1), order=0), "hilbert"))
_NONE = "SELECT CAST(0 AS BIGINT) AS violations"


@query("curve_hilbert_stretched_3d", _NONE)
def _(spark, d):
    """Violations of contiguity and of using each index once, on stretched boxes."""
    out = None
    for cells in ((4, 8, 8), (2, 6, 4), (8, 4, 12), (16, 4, 4)):
        dom = Domain(cells, (1, 1, 1), order=0)
        line = lattice(spark, dom).withColumn("curve_idx", curves.hilbert_index(dom))
        bad = curves.gaps(line, dom).agg(F.count("*").alias("n")).unionByName(line.agg((F.count("*") - F.countDistinct("curve_idx") + F.max("curve_idx") + 1 - F.count("*")).alias("n")))
        out = bad if out is None else out.unionByName(bad)
    return out.agg(F.sum("n").alias("violations"))


@query("curve_gaps", _NONE)
def _(spark, d):
    parts = [curves.gaps(lattice(spark, dom).withColumn("curve_idx", curves.INDEX[k](dom)), dom).agg(F.count("*").alias("n")) for dom, k in ((_SQUARE, "snake"), (_SQUARE, "hilbert"), (_CUBE, "snake"), (_CUBE, "hilbert"), (_LONG2, "hilbert"))]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.agg(F.sum("n").alias("violations"))


query("curve_by_load", twins.with_(twins.load(W["w7"])) + "SELECT step, tile_id, row_number() OVER (PARTITION BY step ORDER BY load_u DESC, tile_id) - 1 AS curve_idx FROM load")(lambda s, d: curves.by_load(load_of(s, d, "w7")).select("step", "tile_id", "curve_idx"))

# Cuts.
_ASG = "SELECT step, tile_id, load_u, pe FROM asg"
query("cut_prefix_1d", twins.with_(DOCS, twins.prefix("load", ["step"], "curve_idx", 8, "pe", "asg")) + "SELECT tile_id, load_u, pe FROM asg")(lambda s, d: cuts.cut_prefix(doc_load(s, d), 8).select("tile_id", "load_u", "pe"))
query("cut_prefix_2d", twins.with_(twins.assign(W["w7"], "hilbert")) + _ASG)(lambda s, d: assigned(s, d, "w7", "hilbert").select("step", "tile_id", "load_u", "pe"))
query("cut_greedy", twins.with_(twins.assign(W["w7"], "greedy_hilbert")) + _ASG)(lambda s, d: assigned(s, d, "w7", "greedy_hilbert").select("step", "tile_id", "load_u", "pe"))
query("cut_adaptive", twins.with_(twins.assign(W["w7"], "adaptive_hilbert")) + _ASG)(lambda s, d: assigned(s, d, "w7", "adaptive_hilbert").select("step", "tile_id", "load_u", "pe"))


def _repaired(v: View, n: int, scheme: str = "hilbert") -> str:
    """asg with every group used: cuts shifted as the text says, on rows."""
    return ", ".join([
        twins.assign(v, scheme, n).replace("asg AS", "raw AS"),
        f"pes AS (SELECT k FROM generate_series(0, {n - 1}) g(k))",
        "cnt2 AS (SELECT step, pe, count(*) AS c FROM raw GROUP BY ALL)",
        "cut AS (SELECT s.step, k, coalesce((SELECT sum(c) FROM cnt2 WHERE cnt2.step = s.step AND cnt2.pe < k), 0) AS c FROM (SELECT DISTINCT step FROM raw) s, pes)",
        f"fix AS (SELECT step, k, least(k + max(c - k) OVER (PARTITION BY step ORDER BY k ROWS UNBOUNDED PRECEDING), {v.dom.n_tiles} - ({n} - k)) AS c FROM cut)",
        "ends AS (SELECT step, k, c, lead(c, 1, 1000000000000) OVER (PARTITION BY step ORDER BY k) AS e FROM fix)",
        "asg AS (SELECT raw.* EXCLUDE (pe), CAST(ends.k AS INTEGER) AS pe FROM raw JOIN ends ON ends.step = raw.step AND raw.curve_idx >= ends.c AND raw.curve_idx < ends.e)",
    ])


query("cut_nonempty", twins.with_(_repaired(W["w6"], 256)) + "SELECT step, tile_id, pe FROM asg")(lambda s, d: assigned(s, d, "w6", "hilbert", 256, (4, 8, 8), nonempty=True).select("step", "tile_id", "pe"))
_BENCH = "load AS (SELECT row_number() OVER (ORDER BY item_id) - 1 AS i, CAST(length(text) AS BIGINT) AS l FROM benchmark)"


@query("cut_minimax", f"WITH {_BENCH}, c AS (SELECT i, sum(l) OVER (ORDER BY i) AS c FROM load), n AS (SELECT count(*) AS m, sum(l) AS t FROM load) SELECT CAST(min(greatest(a.c, b.c - a.c, t - b.c)) AS BIGINT) AS bottleneck_u FROM c a JOIN c b ON a.i <= b.i, n")
def _(spark, d):
    line = spark.read.parquet(f"{d}/benchmark.parquet").select(F.lit(0).alias("step"), F.col("item_id").alias("curve_idx"), F.length("text").cast("bigint").alias("load_u"))
    return cuts.minimax(line, 3).select("bottleneck_u")


query("cut_blocked", twins.with_(twins.assign(W["w7"], "hilbert")) + "SELECT curve_idx, sum(load_u) OVER (ORDER BY curve_idx) AS cum_u FROM asg WHERE step = 25")(lambda s, d: cuts.prefix_sum_blocked(assigned(s, d, "w7", "hilbert").where("step = 25"), 20).select("curve_idx", "cum_u"))


@query("cut_keys_assign", twins.with_(twins.assign(W["w7"], "hilbert")) + "SELECT p.step, pe, count(*) AS n FROM p JOIN asg ON asg.step = p.step AND asg.tx = cx // 10 AND asg.ty = cy // 10 GROUP BY ALL")
def _(spark, d):
    """Particles find their group by n_pe broadcast keys, without a join with tiles."""
    v = W["w7"]
    keys = cuts.first_indices(assigned(spark, d, "w7", "hilbert"), v.n_pe)
    rows = curves.index_particles(bin_particles(v.particles(spark, d), v.dom), v.dom)
    return cuts.assign_by_cuts(rows, keys).groupBy("step", "pe").agg(F.count("*").alias("n"))


@query("cut_bounds", _NONE)
def _(spark, d):
    out = None
    for view, scheme in (("w7", "hilbert"), ("w9", "snake"), ("w6", "hilbert")):
        a = assigned(spark, d, view, scheme)
        n = W[view].n_pe
        top = a.groupBy("step").agg(F.max("load_u").alias("t"), F.sum("load_u").alias("s"))
        bad = metrics.pe_loads(a).select("step", F.col("load_u").alias("l")).join(top, "step").where(F.col("l") * n > F.col("s") + F.col("t") * n).agg(F.count("*").alias("n"))
        out = bad if out is None else out.unionByName(bad)
    return out.agg(F.sum("n").alias("violations"))


@query("cut_ntile_control", twins.with_(twins.assign(W["w7"], "hilbert")) + "SELECT step, pe, sum(load_u) AS load_u FROM (SELECT step, load_u, ntile(16) OVER (PARTITION BY step ORDER BY curve_idx) - 1 AS pe FROM asg) GROUP BY ALL")
def _(spark, d):
    from pyspark.sql.window import Window

    line = decomp.ordered(load_of(spark, d, "w7"), W["w7"].dom, "hilbert")
    return line.withColumn("pe", F.ntile(16).over(Window.partitionBy("step").orderBy("curve_idx")) - 1).groupBy("step", "pe").agg(F.sum("load_u").alias("load_u"))


# Decompositions: the full maps' loads by group.
_PE = "SELECT step, pe, count(*) AS n_tiles, sum(load_u) AS load_u FROM asg GROUP BY ALL"


def _part(name: str, view: str, scheme: str, weight=None) -> None:
    query(name, twins.with_(twins.assign(W[view], scheme)) + _PE)(lambda s, d: metrics.pe_loads(assigned(s, d, view, scheme)))


for _view in ("w1", "w5", "w7", "w9"):
    for _scheme in ("uniform", "one_axis", "rectilinear", "jagged", "snake", "hilbert", "by_load"):
        _part(f"part_{_scheme}_{_view}", _view, _scheme)
for _scheme in ("uniform", "rectilinear", "axis_projection", "jagged", "snake", "hilbert"):
    _part(f"part_{_scheme}_w6", "w6", _scheme)
for _name, _view, _scheme in (("part_uniform_w2", "w2", "uniform"), ("part_hilbert_w2", "w2", "hilbert"), ("part_hilbert_w10", "w10", "hilbert"), ("part_greedy_hilbert_w7", "w7", "greedy_hilbert"), ("part_greedy_snake_w7", "w7", "greedy_snake")):
    _part(_name, _view, _scheme)
for _scheme in ("rectilinear", "jagged"):

    @query(f"part_{_scheme}_cells_w5", twins.with_(twins.assign(_CELLS["w5"], _scheme)) + _PE)
    def _(spark, d, scheme=_scheme):
        v = _CELLS["w5"]
        return metrics.pe_loads(decomp.decompose(loads.load_array(v.particles(spark, d), v.dom, v.weight), v.dom, v.n_pe, scheme, v.grid))


@query("part_rectilinear_refined_w7", _NONE)
def _(spark, d):
    """Tiles without a group or outside the grid: none."""
    out = assigned(spark, d, "w7", "rectilinear_refined")
    return out.agg((F.lit(3 * W["w7"].dom.n_tiles) - F.count_if(F.col("pe").between(0, 15))).alias("violations"))


# Rebalancing on the wake: how often a map is made.
def wake(spark, d, every: int | None, scheme: str = "hilbert", view: str = "w9", n_pe: int | None = None) -> DataFrame:
    v = W[view]
    make = lambda x: decomp.decompose(x, v.dom, n_pe or v.n_pe, scheme, v.grid if n_pe is None else None)
    return rebalance.run(load_of(spark, d, view), make, every)


def _wake_sql(every: int | None, scheme: str = "hilbert", n_pe: int | None = None, view: str = "w9", grid=None) -> str:
    epoch = "0" if every is None else f"a.step - a.step % {every}"
    return twins.assign(W[view], scheme, n_pe, grid) + f", held AS (SELECT a.step, a.tile_id, a.load_u, a.n_part, a.n_cells, b.pe FROM load a JOIN asg b ON b.step = {epoch} AND b.tile_id = a.tile_id)"


for _name, _every, _scheme in (("bal_never", None, "uniform"), ("bal_initial", None, "hilbert"), ("bal_every_k", 40, "hilbert")):
    query(_name, twins.with_(_wake_sql(_every, _scheme)) + twins.IMBALANCE.format(n=32, asg="held"))(lambda s, d, e=_every, c=_scheme: metrics.imbalance(wake(s, d, e, c), 32))

_KS = (20, 40, 80, 160)


@query("bal_interval_sweep", " UNION ALL ".join(f"SELECT {k} AS every, max(imbalance) AS peak, round(avg(imbalance), 6) AS mean FROM ({twins.with_(_wake_sql(k))} {twins.IMBALANCE.format(n=32, asg='held')})" for k in _KS))
def _(spark, d):
    out = None
    for k in _KS:
        row = metrics.imbalance_summary(metrics.imbalance(wake(spark, d, k), 32)).withColumn("every", F.lit(k))
        out = row if out is None else out.unionByName(row)
    return out


_MIG = "SELECT a.step AS epoch, b.pe AS src_pe, a.pe AS dst_pe, count(*) AS n_tiles, sum(a.n_part) AS n_part, sum(a.n_cells) AS n_cells FROM asg a JOIN asg b ON b.step = a.step - 40 AND a.tile_id = b.tile_id AND a.pe <> b.pe WHERE a.step % 40 = 0 GROUP BY ALL"


def _plan(spark, d):
    return rebalance.migration(assigned(spark, d, "w9", "hilbert").where("step % 40 = 0"), 40)


query("bal_migration", twins.with_(twins.assign(W["w9"], "hilbert")) + _MIG)(_plan)
query("bal_messages_grouped", twins.with_(twins.assign(W["w9"], "hilbert")) + f"SELECT epoch, count(*) AS n_messages FROM ({_MIG}) GROUP BY epoch")(lambda s, d: rebalance.messages(_plan(s, d), True))
query("bal_messages_ungrouped", twins.with_(twins.assign(W["w9"], "hilbert")) + f"SELECT epoch, sum(n_tiles) AS n_messages FROM ({_MIG}) GROUP BY epoch")(lambda s, d: rebalance.messages(_plan(s, d), False))


@query("bal_place", _NONE)
def _(spark, d):
    """Rows outside the partition of their group: none."""
    v = W["w7"]
    keys = cuts.first_indices(assigned(spark, d, "w7", "hilbert"), v.n_pe)
    rows = cuts.assign_by_cuts(curves.index_particles(bin_particles(v.particles(spark, d), v.dom), v.dom), keys)
    return decomp.place(rows, v.n_pe).withColumn("at", F.spark_partition_id()).agg(F.count_if(F.col("at") != F.col("pe")).alias("violations"))


@query("bal_threshold")
def _(spark, d):
    v = W["w9"]
    rows = rebalance.threshold(load_of(spark, d, "w9").cache(), lambda x: decomp.decompose(x, v.dom, 32, "hilbert"), 32, 1.2)
    return spark.createDataFrame(rows, "step int, imbalance double, remade boolean")


# Measures of balance.
def _imb(view: str, scheme: str, n: int):
    return lambda s, d: metrics.imbalance(assigned(s, d, view, scheme), n)


query("m_imbalance", twins.with_(twins.assign(W["w7"], "hilbert")) + twins.IMBALANCE.format(n=16, asg="asg"))(_imb("w7", "hilbert", 16))
query("m_imbalance_particles", twins.with_(twins.assign(W["w7"], "hilbert")) + twins.IMBALANCE.format(n=16, asg="(SELECT step, pe, n_part AS load_u FROM asg)"))(lambda s, d: metrics.imbalance(assigned(s, d, "w7", "hilbert"), 16, what="n_part"))
query("m_peak_mean", twins.with_(_wake_sql(40)) + f"SELECT max(imbalance) AS peak, round(avg(imbalance), 6) AS mean FROM ({twins.IMBALANCE.format(n=32, asg='held')})")(lambda s, d: metrics.imbalance_summary(metrics.imbalance(wake(s, d, 40), 32)))
query("m_cumulative_balance", twins.with_(_wake_sql(40)) + f"SELECT round(CAST(sum(max_u) * 32 AS DOUBLE) / sum(total_u), 6) AS cumulative FROM ({twins.IMBALANCE.format(n=32, asg='held')})")(lambda s, d: metrics.cumulative_balance(metrics.imbalance(wake(s, d, 40), 32), 32))
_CONC = "SELECT step, tile_id, n_part, sum(n_part) OVER (PARTITION BY step ORDER BY n_part DESC, tile_id ROWS UNBOUNDED PRECEDING) AS c, sum(n_part) OVER (PARTITION BY step) AS n, row_number() OVER (PARTITION BY step ORDER BY n_part DESC, tile_id) AS r, count(*) OVER (PARTITION BY step) AS m"
query("m_concentration", twins.with_(twins.load(W["w6"])) + f"SELECT step, min(r) AS n_tiles, round(CAST(min(r) AS DOUBLE) / min(m), 6) AS share FROM ({_CONC} FROM load) WHERE c * 100 >= n * 70 GROUP BY step")(lambda s, d: metrics.concentration(load_of(s, d, "w6")))
query("m_hot_spread", twins.with_(twins.assign(W["w6"], "hilbert")) + f"SELECT step, count(DISTINCT pe) AS n_pe, count(*) AS n_tiles FROM ({_CONC}, pe FROM asg) WHERE (c - n_part) * 100 < n * 70 GROUP BY step")(lambda s, d: metrics.hot_spread(assigned(s, d, "w6", "hilbert")))
_RADIUS = "(cx * 2 + 1 - 160) * (cx * 2 + 1 - 160) + (cy * 2 + 1 - 160) * (cy * 2 + 1 - 160) + (cz * 2 + 1 - 160) * (cz * 2 + 1 - 160)"


@query("m_within_radius", twins.with_(twins.particles(W["w6"])) + f"SELECT step, r, round(CAST(count(*) FILTER ({_RADIUS} <= 4 * r * r) AS DOUBLE) / count(*), 6) AS inside, round(CAST(4.1887902047863905 AS DOUBLE) * r * r * r / 4096000, 6) AS volume FROM p, (VALUES (25), (50)) g(r) GROUP BY ALL")
def _(spark, d):
    rows = W["w6"].particles(spark, d).withColumn("r", F.explode(F.array(F.lit(25), F.lit(50))))
    return rows.groupBy("step", "r").agg(F.round(F.count_if(F.expr(f"{_RADIUS} <= 4 * r * r")) / F.count("*"), 6).alias("inside")).withColumn("volume", F.round(F.lit(4.1887902047863905) * F.col("r") * F.col("r") * F.col("r") / 4096000, 6))


query("m_tiles_per_pe", twins.with_(twins.assign(W["w6"], "hilbert")) + "SELECT step, round(CAST(sum(c) AS DOUBLE) / 64, 6) AS mean_tiles, CASE WHEN count(*) < 64 THEN 0 ELSE min(c) END AS least_tiles FROM (SELECT step, pe, count(*) AS c FROM asg GROUP BY ALL) GROUP BY step")(lambda s, d: metrics.tiles_per_pe(assigned(s, d, "w6", "hilbert"), 64))
query("m_over_full", twins.with_(twins.load(W["w6"])) + "SELECT step, count(*) AS n_tiles, count(*) FILTER (load_u * 64 > t) AS over_full FROM (SELECT *, sum(load_u) OVER (PARTITION BY step) AS t FROM load) GROUP BY step")(
    lambda s, d: load_of(s, d, "w6").join(F.broadcast(loads.ideal_load(load_of(s, d, "w6"), 64)), "step").groupBy("step").agg(F.count("*").alias("n_tiles"), F.count_if(F.col("load_u") * 64 > F.col("total_u")).alias("over_full"))
)


@query("m_gap_optimum", f"WITH {_BENCH}, l2 AS (SELECT 0 AS step, i AS curve_idx, l AS load_u FROM load), {twins.prefix('l2', ['step'], 'curve_idx', 3, 'pe', 'asg')}, c AS (SELECT i, sum(l) OVER (ORDER BY i) AS c FROM load), n AS (SELECT sum(l) AS t FROM load), best AS (SELECT min(greatest(a.c, b.c - a.c, t - b.c)) AS o FROM c a JOIN c b ON a.i <= b.i, n) SELECT round(CAST((SELECT max(s) FROM (SELECT sum(load_u) AS s FROM asg GROUP BY pe)) AS DOUBLE) / o, 6) AS gap FROM best")
def _(spark, d):
    line = spark.read.parquet(f"{d}/benchmark.parquet").select(F.lit(0).alias("step"), F.col("item_id").alias("curve_idx"), F.length("text").cast("bigint").alias("load_u"))
    own = metrics.pe_loads(cuts.cut_prefix(line, 3)).groupBy("step").agg(F.max("load_u").alias("m"))
    return own.join(cuts.minimax(line, 3), "step").select(F.round(F.col("m") / F.col("bottleneck_u"), 6).alias("gap"))


# Experiments on balance alone.
_SCHEMES = ("uniform", "rectilinear", "jagged", "snake", "hilbert")


def _compare(name: str, view: str) -> None:
    v = W[view]
    sql = " UNION ALL ".join(f"SELECT '{c}' AS scheme, * FROM ({twins.with_(twins.assign(v, c))} {twins.IMBALANCE.format(n=v.n_pe, asg='asg')})" for c in _SCHEMES)

    @query(name, sql)
    def _(spark, d):
        base, out = load_of(spark, d, view), None
        for c in _SCHEMES:
            row = metrics.imbalance(decomp.decompose(base, v.dom, v.n_pe, c, v.grid), v.n_pe).withColumn("scheme", F.lit(c))
            out = row if out is None else out.unionByName(row)
        return out


_compare("exp_stripe_four", "w5")
_compare("exp_ball_times", "w7")
query("exp_wake_curve", twins.with_(twins.assign(W["w10"], "hilbert")) + twins.IMBALANCE.format(n=32, asg="asg"))(_imb("w10", "hilbert", 32))
_SERIES = ((128, "uniform", None), (128, "hilbert", 40), (8, "uniform", None), (8, "hilbert", 40))
_SGRID = {128: (16, 8), 8: (4, 2)}


@query("exp_wake_series", " UNION ALL ".join(f"SELECT {n} AS n_pe, '{c}' AS scheme, * FROM ({twins.with_(_wake_sql(k, c, n, grid=_SGRID[n]))} {twins.IMBALANCE.format(n=n, asg='held')})" for n, c, k in _SERIES))
def _(spark, d):
    base, v, out = load_of(spark, d, "w9"), W["w9"], None
    for n, c, k in _SERIES:
        held = rebalance.run(base, lambda x, n=n, c=c: decomp.decompose(x, v.dom, n, c, _SGRID[n]), k)
        row = metrics.imbalance(held, n).withColumns({"n_pe": F.lit(n), "scheme": F.lit(c)})
        out = row if out is None else out.unionByName(row)
    return out


@query("exp_text_skew", " UNION ALL ".join(f"SELECT {n} AS n_pe, * EXCLUDE (step) FROM ({twins.with_(DOCS, twins.prefix('load', ['step'], 'curve_idx', n, 'pe', 'asg'))} {twins.IMBALANCE.format(n=n, asg='asg')})" for n in (4, 16, 64)))
def _(spark, d):
    base, out = doc_load(spark, d), None
    for n in (4, 16, 64):
        row = metrics.imbalance(cuts.cut_prefix(base, n), n).drop("step").withColumn("n_pe", F.lit(n))
        out = row if out is None else out.unionByName(row)
    return out


_CLOUD = replace(W["w2"], dom=Domain((8, 8, 8), (1, 1, 1), order=0))


@query("exp_cloud", "SELECT label AS species, cx, cy, cz, count(*) AS n FROM (SELECT label, CAST(floor((CAST(embedding[1] AS DOUBLE) + 1) * 4) AS BIGINT) AS cx, CAST(floor((CAST(embedding[2] AS DOUBLE) + 1) * 4) AS BIGINT) AS cy, CAST(floor((CAST(embedding[3] AS DOUBLE) + 1) * 4) AS BIGINT) AS cz FROM embeddings) GROUP BY ALL")
def _(spark, d):
    rows = spark.read.parquet(f"{d}/embeddings.parquet").select(F.col("label").alias("species"), *[F.floor((F.col("embedding")[k].cast("double") + 1) * 4).alias(c) for k, c in enumerate(("cx", "cy", "cz"))])
    return rows.groupBy("species", "cx", "cy", "cz").agg(F.count("*").alias("n"))


@query("exp_species_cube", twins.with_(twins.assign(W["w9"], "hilbert")) + "SELECT p.step, species, pe, count(*) AS n, grouping(species, pe) AS level FROM p JOIN asg ON asg.step = p.step AND asg.tx = cx // 8 AND asg.ty = cy // 8 GROUP BY p.step, CUBE (species, pe)")
def _(spark, d):
    v = W["w9"]
    rows = loads.density(v.particles(spark, d), v.dom).join(assigned(spark, d, "w9", "hilbert").select("step", "tile_id", "pe"), ["step", "tile_id"])
    return rows.groupingSets([["step", "species", "pe"], ["step", "species"], ["step", "pe"], ["step"]], "step", "species", "pe").agg(F.sum("n_part").alias("n"), (F.grouping("species") * 2 + F.grouping("pe")).cast("bigint").alias("level"))


@lru_cache
def names() -> tuple[str, ...]:
    from . import REGISTRY

    return tuple(REGISTRY)
