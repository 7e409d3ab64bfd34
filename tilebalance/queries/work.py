"""Heavy and light tiles, deposits, skewed keys, the cost model and the experiments that use them."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .. import cost, cuts, decomp, load as loads, metrics, pic, threads
from ..lattice import Domain, bin_particles, with_tile_side
from ..operators import skew
from ..views import VIEWS as W
from ..views import _warm
from . import query, twins
from .balance import _NONE, _repaired, _wake_sql, assigned, load_of, doc_load, wake


def _marked(t: int, source: str = "asg") -> str:
    return f"cls AS (SELECT *, load_u * {t} >= sum(load_u) OVER (PARTITION BY step, pe) OR count(*) OVER (PARTITION BY step, pe) < {t} AS is_heavy FROM {source})"


def _schedule(t: int, light: str, name: str = "tim", reduce_cost: int = 0, source: str = "cls") -> str:
    """name(step, pe, load_u, n_tiles, n_heavy, time_t): a recursive walk over the light tiles with a list of clocks."""
    clocks = "[" + ", ".join(["CAST(0 AS BIGINT)"] * t) + "]"
    return (
        f"{name}_l AS (SELECT step, pe, load_u, row_number() OVER (PARTITION BY step, pe ORDER BY curve_idx) AS r FROM {source} WHERE {light}), "
        f"{name}_w AS (SELECT step, pe, CAST(0 AS BIGINT) AS r, {clocks} AS c FROM (SELECT DISTINCT step, pe FROM {source}) UNION ALL "
        f"SELECT w.step, w.pe, w.r + 1, list_transform(w.c, lambda x, i: CASE WHEN i = list_position(w.c, list_min(w.c)) THEN x + l.load_u ELSE x END) FROM {name}_w w JOIN {name}_l l ON l.step = w.step AND l.pe = w.pe AND l.r = w.r + 1), "
        f"{name}_m AS (SELECT step, pe, max(list_max(c)) AS m FROM {name}_w GROUP BY ALL), "
        f"{name} AS (SELECT a.step, a.pe, a.load_u, a.n_tiles, a.n_heavy, CAST(m.m * {t} + a.shared AS BIGINT) AS time_t FROM (SELECT step, pe, sum(load_u) AS load_u, count(*) AS n_tiles, count(*) FILTER (is_heavy) AS n_heavy, "
        f"coalesce(sum(load_u) FILTER (NOT ({light})), 0) + {reduce_cost * t * t} * coalesce(sum(n_cells) FILTER (NOT ({light})), 0) AS shared FROM {source} GROUP BY ALL) a JOIN {name}_m m USING (step, pe))"
    )


_LIGHT = {"hybrid": "NOT is_heavy", "light_only": "TRUE", "heavy_only": "FALSE", "no_tiles": "FALSE"}

query("thr_classify_w7", twins.with_(twins.assign(W["w7"], "hilbert"), _marked(4)) + "SELECT step, tile_id, is_heavy FROM cls")(lambda s, d: threads.classify(assigned(s, d, "w7", "hilbert"), 4).select("step", "tile_id", "is_heavy"))
_DOCCUT = twins.with_("load AS (SELECT 0 AS step, doc_id // 8 AS tile_id, CAST(sum(n_chars) AS BIGINT) AS load_u, doc_id // 8 AS curve_idx FROM documents GROUP BY ALL)", twins.prefix("load", ["step"], "curve_idx", 8, "pe", "asg"), _marked(4))
query("thr_classify_docs", _DOCCUT + "SELECT tile_id, pe, is_heavy FROM cls")(lambda s, d: threads.classify(cuts.cut_prefix(doc_load(s, d), 8), 4).select("tile_id", "pe", "is_heavy"))
for _mode in ("hybrid", "light_only", "heavy_only", "no_tiles"):
    _red = 1 if _mode == "no_tiles" else 0
    query(f"thr_{_mode}_w6", twins.with_(twins.assign(W["w6"], "hilbert"), _marked(4), _schedule(4, _LIGHT[_mode], reduce_cost=_red)) + "SELECT * FROM tim")(lambda s, d, m=_mode, r=_red: threads.pe_time(assigned(s, d, "w6", "hilbert"), 4, m, reduce_cost=r))
query(
    "thr_task_counts",
    twins.with_(twins.assign(W["w7"], "hilbert"), _marked(4)) + "SELECT step, tile_id, CAST(CASE WHEN is_heavy THEN greatest(1, least(4, CASE WHEN n > 0 THEN (8 * n_part + n) // (2 * n) ELSE 1 END)) ELSE 1 END AS INTEGER) AS slots FROM (SELECT *, sum(n_part) OVER (PARTITION BY step, pe) AS n FROM cls)",
)(lambda s, d: threads.task_threads(assigned(s, d, "w7", "hilbert"), 4).select("step", "tile_id", "slots"))
query("thr_alpha", twins.with_(twins.load(W["w7"])) + "SELECT step, max(load_u) AS max_tile_u, sum(load_u) AS total_u, greatest(1.0, max(load_u) * 16 / CAST(sum(load_u) AS DOUBLE)) AS alpha FROM load GROUP BY step")(lambda s, d: threads.alpha(load_of(s, d, "w7"), 16))


@query("thr_split_heavy", "WITH o AS (SELECT o_orderkey AS pid, o_custkey // 16 AS tile_id FROM orders), c AS (SELECT tile_id, count(*) AS n FROM o GROUP BY 1), h AS (SELECT tile_id FROM c, (SELECT avg(n) AS a FROM c) WHERE n > a) SELECT tile_id, CASE WHEN tile_id IN (SELECT * FROM h) THEN pid % 4 ELSE 0 END AS slot, count(*) AS n FROM o GROUP BY ALL")
def _(spark, d):
    rows = spark.read.parquet(f"{d}/orders.parquet").selectExpr("o_orderkey AS pid", "o_custkey div 16 AS tile_id")
    counts = rows.groupBy("tile_id").agg(F.count("*").alias("n"))
    heavy = counts.crossJoin(F.broadcast(counts.agg(F.avg("n").alias("a")))).where("n > a")
    return threads.split_heavy(rows, heavy, 4).groupBy("tile_id", "slot").agg(F.count("*").alias("n"))


_TILES = twins.with_(twins.assign(W["w6"], "hilbert", 16), _marked(4), _schedule(4, "NOT is_heavy"))
query("thr_slot_plan", _TILES + "SELECT step, pe, max(n_heavy) AS n_heavy, CAST(max(time_t) AS BIGINT) AS time_t FROM tim GROUP BY step, pe")(lambda s, d: threads.plan_time(threads.slot_plan(assigned(s, d, "w6", "hilbert", 16), 4), 4))


@query("thr_hybrid_place", f"SELECT step, cx, cy, cz, count(*) AS n FROM ({W['w6'].sql()}) GROUP BY ALL")
def _(spark, d):
    """Counts of cells made in the placed partitions: one private copy for each partition, copies added up."""
    v = W["w6"]
    plan = threads.slot_plan(assigned(spark, d, "w6", "hilbert", 16), 4)
    placed = threads.place_hybrid(bin_particles(v.particles(spark, d), v.dom), plan, 16, 4)
    return threads.private_sums(placed, ["step", *v.dom.ccols], {"n": F.lit(1).cast("bigint")})


query("thr_wide", twins.with_(twins.assign(W["w6"], "uniform", 16, (2, 2, 4))) + "SELECT step, CAST(max(s) AS DOUBLE) / 4 AS core, sum(s) AS total_u FROM (SELECT step, pe, sum(load_u) AS s FROM asg GROUP BY ALL) GROUP BY step")(
    lambda s, d: metrics.pe_loads(assigned(s, d, "w6", "uniform", 16, (2, 2, 4))).groupBy("step").agg((F.max("load_u") / 4).alias("core"), F.sum("load_u").alias("total_u"))
)


@query("thr_task_makespan", _NONE)
def _(spark, d):
    """Groups whose task makespan is below total/threads or above one thread's time: none."""
    a = assigned(spark, d, "w7", "hilbert")
    own = threads.task_time(a, 4).join(metrics.pe_loads(a), ["step", "pe"])
    return own.agg(F.count_if((F.col("makespan") * 4 < F.col("load_u") - 1e-6) | (F.col("makespan") > F.col("load_u") + 1e-6)).alias("violations"))


@query("thr_taskfarm", _NONE)
def _(spark, d):
    a = assigned(spark, d, "w7", "uniform")
    farm = threads.taskfarm(a, 16)
    top = a.groupBy("step").agg(F.max("load_u").alias("t"), F.sum("load_u").alias("s"), F.count("*").alias("m"))
    return farm.join(top, "step").agg(F.count_if((F.col("makespan") * 16 < F.col("s")) | (F.col("makespan") * 16 > F.col("s") + F.col("t") * 15) | (F.col("n_tasks") != F.col("m")) | (F.col("stolen") < 1)).alias("violations"))


@query("thr_bounds", _NONE)
def _(spark, d):
    """Light makespans outside [largest tile or mean, mean + (1 - 1/T) largest tile], and hybrid maxima above light_only's: none."""
    a = assigned(spark, d, "w6", "hilbert")
    top = a.groupBy("step", "pe").agg(F.max("load_u").alias("t"))
    light = threads.pe_time(a, 4, "light_only").join(top, ["step", "pe"])
    bad = light.agg(F.count_if((F.col("time_t") < F.greatest(F.col("t") * 4, F.col("load_u"))) | (F.col("time_t") > F.col("load_u") + 3 * F.col("t"))).alias("n"))
    best = metrics.core_load(threads.pe_time(a, 4, "hybrid")).select("step", F.col("core_t").alias("h")).join(metrics.core_load(light), "step")
    return bad.unionByName(best.agg(F.count_if(F.col("h") > F.col("core_t")).alias("n"))).agg(F.sum("n").alias("violations"))


# Deposits: positions in milli-cells on the warm view.
_SMALL = Domain((32, 32), (8, 8))
_POS = "SELECT l_orderkey AS pid, l_partkey * 32000 // (SELECT count(*) FROM part) AS x, l_orderkey * 32000 // (SELECT count(*) FROM orders) AS y, CAST(round(100 * l_discount) AS BIGINT) - 5 AS vx, CAST(round(100 * l_tax) AS BIGINT) - 4 AS vy FROM lineitem"


def positions(spark, d):
    from ..views import extent

    np_, no = extent(spark, d, "part"), extent(spark, d, "orders")
    return spark.read.parquet(f"{d}/lineitem.parquet").selectExpr("l_orderkey AS pid", f"l_partkey * 32000 div {np_} AS x", f"l_orderkey * 32000 div {no} AS y", "cast(round(100 * l_discount) AS bigint) - 5 AS vx", "cast(round(100 * l_tax) AS bigint) - 4 AS vy")


def _shape(order: int, a: str) -> str:
    o = f"(({a} % 1000) / 1000.0 - 0.5)"
    terms = {0: ["(0, 1.0)"], 1: [f"(-1, greatest(0.0, -{o}))", f"(0, 1 - abs({o}))", f"(1, greatest(0.0, {o}))"], 2: [f"(-1, (0.5 - {o}) * (0.5 - {o}) / 2)", f"(0, 0.75 - {o} * {o})", f"(1, (0.5 + {o}) * (0.5 + {o}) / 2)"]}[order]
    return "[" + ", ".join(f"{{'k': CAST({t[1:-1].split(',', 1)[0]} AS INTEGER), 'w': CAST({t[1:-1].split(',', 1)[1]} AS DOUBLE)}}" for t in terms) + "]"


def _deposit_sql(order: int) -> str:
    return (
        f"WITH q AS ({_POS}), e1 AS (SELECT x, y, unnest({_shape(order, 'x')}) AS a FROM q), e2 AS (SELECT x, a, unnest({_shape(order, 'y')}) AS b, y FROM e1) "
        "SELECT (x // 1000 + a.k + 32) % 32 AS cx, (y // 1000 + b.k + 32) % 32 AS cy, round(sum(a.w * b.w), 4) AS value FROM e2 GROUP BY ALL"
    )


for _name, _order, _strategy in (("dep_private", 2, "private"), ("dep_atomic", 2, "atomic"), ("dep_nearest", 0, "private"), ("dep_linear", 1, "private"), ("dep_quadratic", 2, "private")):
    query(_name, _deposit_sql(_order))(lambda s, d, o=_order, g=_strategy: pic.deposit(positions(s, d), _SMALL, o, g).select("cx", "cy", F.round("value", 4).alias("value")))


@query("dep_conserve", _NONE)
def _(spark, d):
    """Deposits whose sum is not the number of particles: none."""
    rows = positions(spark, d)
    n = rows.agg(F.count("*").alias("n"))
    out = None
    for order in (0, 1, 2):
        s = pic.deposit(rows, _SMALL, order).agg(F.sum("value").alias("s"))
        out = s if out is None else out.unionByName(s)
    return out.crossJoin(F.broadcast(n)).agg(F.count_if(F.abs(F.col("s") - F.col("n")) > 1e-6 * F.col("n")).alias("violations"))


query("pic_push", f"SELECT (x + vx * 250 + 32000) % 32000 AS x, (y + vy * 250 + 32000) % 32000 AS y, count(*) AS n FROM ({_POS}) GROUP BY ALL")(lambda s, d: pic.push(positions(s, d), _SMALL, 250).groupBy("x", "y").agg(F.count("*").alias("n")))


def _safe(spark):
    if not spark.sparkContext.getCheckpointDir() and not spark.conf.get("spark.checkpoint.dir", None):
        import tempfile

        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="shared-"))


@query("pic_field")
def _(spark, d):
    _safe(spark)
    return pic.field(pic.deposit(positions(spark, d), _SMALL), _SMALL, 8).select("cx", "cy", F.round("value", 6).alias("value"))


@query("pic_gather")
def _(spark, d):
    _safe(spark)
    rows = positions(spark, d)
    return pic.gather(rows, pic.field(pic.deposit(rows, _SMALL), _SMALL, 4), _SMALL)


@query("pic_steps")
def _(spark, d):
    """A few steps of the loop with the imbalance of a map that is renewed every second step."""
    _safe(spark)
    rows, out, keep = positions(spark, d), None, None
    for step in range(4):
        rows = pic.push(rows, _SMALL, 400)
        if step % 2 == 1:
            rows = rows.checkpoint()
        cells = rows.selectExpr("x div 1000 AS cx", "y div 1000 AS cy").withColumn("step", F.lit(step))
        load = loads.load_array(cells, _SMALL)
        if step % 2 == 0:
            keep = decomp.decompose(load, _SMALL, 4, "hilbert").select("tile_id", "pe")
        row = metrics.imbalance(load.join(keep, "tile_id"), 4)
        out = row if out is None else out.unionByName(row)
    return out


# Skewed keys.
@query("skew_agg_docs", "SELECT source, count(*) AS n, sum(n_chars) AS chars, max(n_chars) AS longest FROM documents GROUP BY source")
def _(spark, d):
    docs = spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "source", "n_chars")
    return skew.balanced_agg(docs, ["source"], {"n": F.count("*"), "chars": F.sum("n_chars"), "longest": F.max("n_chars")}, {"n": F.sum("n"), "chars": F.sum("chars"), "longest": F.max("longest")})


@query("skew_join_orders", "SELECT o_orderstatus, count(*) AS n, sum(c_nationkey) AS s FROM (SELECT o_orderkey, o_orderstatus, o_custkey % 5 AS k FROM orders) o JOIN (SELECT DISTINCT c_nationkey, c_custkey % 5 AS k FROM customer) c USING (k) GROUP BY ALL")
def _(spark, d):
    orders = spark.read.parquet(f"{d}/orders.parquet").select("o_orderkey", "o_orderstatus", (F.col("o_custkey") % 5).alias("k"))
    other = spark.read.parquet(f"{d}/customer.parquet").select("c_nationkey", (F.col("c_custkey") % 5).alias("k")).distinct()
    return skew.balanced_join(orders, other, ["k"]).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum("c_nationkey").alias("s"))


@query("skew_aqe_join", "SELECT source, sum(n_chars) AS chars, count(quality) AS n FROM documents JOIN labels USING (doc_id) GROUP BY source")
def _(spark, d):
    """The stock answer: a sort-merge join whose skewed partitions Spark splits at run time."""
    docs = spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "source", "n_chars")
    return docs.hint("merge").join(spark.read.parquet(f"{d}/labels.parquet").select("doc_id", "quality"), "doc_id").groupBy("source").agg(F.sum("n_chars").alias("chars"), F.count("quality").alias("n"))


query("skew_hash_mod", twins.with_(twins.load(W["w7"])) + "SELECT step, CAST(tile_id % 16 AS INTEGER) AS pe, sum(load_u) AS load_u FROM load GROUP BY ALL")(lambda s, d: load_of(s, d, "w7").withColumn("pe", F.pmod("tile_id", F.lit(16)).cast("int")).groupBy("step", "pe").agg(F.sum("load_u").alias("load_u")))


# Measures of time.
_CONFIGS = ((64, 1, (4, 4, 4)), (32, 2, (4, 4, 2)), (16, 4, (4, 2, 2)), (4, 16, (2, 2, 1)))


def core_rows(spark, d, view: str, cores: int, modes=("hybrid", "light_only"), ts=(1, 2, 4, 16), steps=None):
    base, v, out = load_of(spark, d, view), W[view], None
    for t in ts:
        n = cores // t
        a = decomp.decompose(base, v.dom, n, "hilbert", decomp.factors(n, v.dom.tiles), nonempty=True)
        for m in modes:
            row = metrics.core_load(threads.pe_time(a, t, m)).select("step", F.lit(cores).alias("cores"), F.lit(t).alias("threads"), F.lit(m).alias("mode"), F.round(F.col("core_t") * F.lit(n) / F.col("total_u"), 6).alias("over_ideal"))
            out = row if out is None else out.unionByName(row)
    return out


def core_sql(view: str, cores: int, modes=("hybrid", "light_only"), ts=(1, 2, 4, 16)) -> str:
    parts = []
    for t in ts:
        n = cores // t
        for m in modes:
            parts.append(f"SELECT * FROM ({twins.with_(_repaired(W[view], n), _marked(t), _schedule(t, _LIGHT[m]))} SELECT step, {cores} AS cores, {t} AS threads, '{m}' AS mode, round(CAST(max(time_t) * {n} AS DOUBLE) / sum(load_u), 6) AS over_ideal FROM tim GROUP BY step)")
    return " UNION ALL ".join(parts)


_CORE = core_sql("w6", 64)
query("m_core_load", _CORE)(lambda s, d: core_rows(s, d, "w6", 64))
query("m_best_config", f"SELECT step, mode, min(over_ideal) AS over_ideal, min_by(threads, over_ideal * 100 + threads / 1000) AS threads FROM ({_CORE}) GROUP BY ALL")(
    lambda s, d: core_rows(s, d, "w6", 64).groupBy("step", "mode").agg(F.min("over_ideal").alias("over_ideal"), F.min_by("threads", F.col("over_ideal") * 100 + F.col("threads") / 1000).alias("threads"))
)
query("m_speedup", f"SELECT step, threads, round(max(over_ideal) FILTER (mode = 'light_only') / max(over_ideal) FILTER (mode = 'hybrid'), 4) AS speedup FROM ({_CORE}) GROUP BY ALL")(
    lambda s, d: core_rows(s, d, "w6", 64).groupBy("step", "threads").pivot("mode", ["hybrid", "light_only"]).agg(F.max("over_ideal")).select("step", "threads", F.round(F.col("light_only") / F.col("hybrid"), 4).alias("speedup"))
)
query("m_thread_sensitivity", f"SELECT step, mode, round((max(over_ideal) - min(over_ideal)) / min(over_ideal), 4) AS spread FROM ({_CORE}) GROUP BY ALL")(
    lambda s, d: core_rows(s, d, "w6", 64).groupBy("step", "mode").agg(F.round((F.max("over_ideal") - F.min("over_ideal")) / F.min("over_ideal"), 4).alias("spread"))
)
query("m_time_norm", f"SELECT step, threads, mode, round(over_ideal / min(over_ideal) OVER (PARTITION BY step), 4) AS time_norm FROM ({_CORE})")(
    lambda s, d: core_rows(s, d, "w6", 64).select("step", "threads", "mode", F.round(F.col("over_ideal") / F.min("over_ideal").over(Window.partitionBy("step")), 4).alias("time_norm"))
)
query("m_throughput_model", f"SELECT step, threads, mode, round(min(over_ideal) OVER (PARTITION BY step) / over_ideal, 4) AS throughput FROM ({_CORE})")(
    lambda s, d: core_rows(s, d, "w6", 64).select("step", "threads", "mode", F.round(F.min("over_ideal").over(Window.partitionBy("step")) / F.col("over_ideal"), 4).alias("throughput"))
)
_SCALE = (8, 32, 128)


def scaling_rows(spark, d):
    out = None
    for c in _SCALE:
        row = core_rows(spark, d, "w6", c, ("hybrid",), (4,))
        out = row if out is None else out.unionByName(row)
    return out.drop("threads", "mode")


_SCALE_SQL = " UNION ALL ".join(f"SELECT step, cores, over_ideal FROM ({core_sql('w6', c, ('hybrid',), (4,))})" for c in _SCALE)
query("m_scaling", f"SELECT step, cores, round(first_value(over_ideal) OVER (PARTITION BY step ORDER BY cores) / over_ideal, 4) AS efficiency FROM ({_SCALE_SQL})")(
    lambda s, d: scaling_rows(s, d).select("step", "cores", F.round(F.first("over_ideal").over(Window.partitionBy("step").orderBy("cores")) / F.col("over_ideal"), 4).alias("efficiency"))
)
query("m_ideal_up_to", f"SELECT step, coalesce(max(cores) FILTER (over_ideal <= 1.5), 0) AS cores FROM ({_SCALE_SQL}) GROUP BY step")(lambda s, d: scaling_rows(s, d).groupBy("step").agg(F.coalesce(F.max(F.when(F.col("over_ideal") <= 1.5, F.col("cores"))), F.lit(0)).alias("cores")))
query("m_heavy_share", twins.with_(_wake_sql(40).replace("b.pe FROM", "b.pe, a.step AS s2 FROM"), _marked(4, "held")) + "SELECT step, count(*) FILTER (is_heavy) AS n_heavy, count(*) AS n_tiles, round(CAST(count(*) FILTER (is_heavy) AS DOUBLE) / count(*), 6) AS share FROM cls GROUP BY step")(
    lambda s, d: metrics.heavy_stats(threads.classify(wake(s, d, 40), 4))
)


def _overhead_sql() -> str:
    parts = []
    for red in (0, 1):
        tiled = twins.with_(twins.assign(W["w1"], "hilbert"), _marked(4), _schedule(4, "NOT is_heavy", reduce_cost=red)) + "SELECT max(time_t) AS a FROM tim"
        whole = twins.with_(twins.assign(W["w1"], "uniform"), _marked(4, "(SELECT *, tile_id AS curve_idx FROM asg)"), _schedule(4, "FALSE", reduce_cost=red)) + "SELECT max(time_t) AS b FROM tim"
        parts.append(f"SELECT {red} AS reduce_cost, CAST(a AS DOUBLE) / CAST(b AS DOUBLE) AS ratio FROM ({tiled}) x, ({whole}) y")
    return " UNION ALL ".join(parts)


@query("m_tile_overhead", _overhead_sql())
def _(spark, d):
    """Modelled time of tiles (hybrid) over untiled groups on the balanced view, with and without the cost of private copies."""
    out = None
    for red in (0, 1):
        a = assigned(spark, d, "w1", "hilbert")
        tiled, whole = metrics.core_load(threads.pe_time(a, 4, "hybrid", reduce_cost=red)), metrics.core_load(threads.pe_time(assigned(spark, d, "w1", "uniform").withColumn("curve_idx", F.col("tile_id")), 4, "no_tiles", reduce_cost=red))
        row = tiled.join(whole.select("step", F.col("core_t").alias("w")), "step").select(F.lit(red).alias("reduce_cost"), (F.col("core_t") / F.col("w")).alias("ratio"))
        out = row if out is None else out.unionByName(row)
    return out


def _dlb_sql() -> str:
    c = cost.Cost()
    move = "SELECT {k} AS every, count(DISTINCT (step, src, dst)) * {lat} AS l, coalesce(sum(n_part * {p} + n_cells * {q}), 0) AS m FROM (SELECT a.step, b.pe AS src, a.pe AS dst, a.n_part, a.n_cells FROM asg a JOIN asg b ON a.tile_id = b.tile_id AND a.pe <> b.pe AND a.step % {k} = 0 AND b.step = a.step - {k})"
    moves = " UNION ALL ".join(move.format(k=k, lat=c.latency, p=c.migrate_part, q=c.migrate_cell) for k in (20, 40, 80))
    return twins.with_(twins.assign(W["w9"], "hilbert"), f"mv AS ({moves})") + "SELECT every, CAST(m + l AS DOUBLE) / CAST((SELECT sum(load_u) * 20 FROM load) + m + l AS DOUBLE) AS share FROM mv"


@query("m_dlb_overhead", _dlb_sql())
def _(spark, d):
    """Modelled share of the run that rebalancing takes: what migrates against what is pushed, by interval."""
    from .. import rebalance

    c, out = cost.Cost(), None
    maps = assigned(spark, d, "w9", "hilbert")
    for k in (20, 40, 80):
        plan = rebalance.migration(maps.where(F.col("step") % k == 0), k).agg(F.coalesce(F.sum(F.col("n_part") * c.migrate_part + F.col("n_cells") * c.migrate_cell), F.lit(0)).alias("m"), (F.count("*") * c.latency).alias("l"))
        work = load_of(spark, d, "w9").agg((F.sum("load_u") * 20).alias("w"))  # 20 steps for each sampled one
        row = plan.crossJoin(F.broadcast(work)).select(F.lit(k).alias("every"), ((F.col("m") + F.col("l")) / (F.col("w") + F.col("m") + F.col("l"))).alias("share"))
        out = row if out is None else out.unionByName(row)
    return out


# Experiments.
_WARM = ((64, 1, (8, 8)), (32, 2, (8, 4)), (16, 4, (4, 4)), (8, 8, (4, 2)), (4, 16, (2, 2)))


@query("exp_warm_threads", " UNION ALL ".join(f"SELECT * FROM ({twins.with_(twins.assign(W['w1'], 'hilbert', n), _marked(t), _schedule(t, 'NOT is_heavy'))} SELECT {n} AS n_pe, {t} AS threads, sum(n_heavy) AS n_heavy, round(CAST(max(time_t) * {n} AS DOUBLE) / sum(load_u), 6) AS over_ideal FROM tim)" for n, t, _ in _WARM))
def _(spark, d):
    base, v, out = load_of(spark, d, "w1"), W["w1"], None
    for n, t, g in _WARM:
        row = threads.pe_time(decomp.decompose(base, v.dom, n, "hilbert", g), t).agg(F.sum("n_heavy").alias("n_heavy"), F.round(F.max("time_t") * n / F.sum("load_u"), 6).alias("over_ideal")).withColumns({"n_pe": F.lit(n), "threads": F.lit(t)})
        out = row if out is None else out.unionByName(row)
    return out


#: Modelled time of one tile side: the push, a fixed cost for each tile and step, and border cells.
_SWEEP = [(c, s) for c, sides in ((256, (8, 16, 32, 64)), (64, (8, 16, 32)), (32, (8, 16)), (20, (5, 10, 20))) for s in sides]
_FIXED, _BORDER = 40, 1


def _sweep_views():
    return [(c, s, replace(_warm(c, s, 4, (2, 2)), dom=with_tile_side(Domain((c, c), (c, c)), s))) for c, s in _SWEEP]


def _sweep_sql() -> str:
    parts = []
    for c, s, v in _sweep_views():
        parts.append(f"SELECT * FROM ({twins.with_(twins.load(v))} SELECT {c} AS cells, {s} AS side, CAST(sum(load_u) + {len(v.dom.cells) and v.dom.n_tiles * (_FIXED + 4 * s * _BORDER)} + greatest(0, max(load_u) * 8 - sum(load_u)) AS BIGINT) AS time_u FROM load)")
    return " UNION ALL ".join(parts)


def sweep_rows(spark, d):
    """Total work, fixed and border costs of tiles, and what a tile larger than an eighth of the work makes seven threads wait."""
    out = None
    for c, s, v in _sweep_views():
        row = loads.load_array(v.particles(spark, d), v.dom, v.weight).agg((F.sum("load_u") + v.dom.n_tiles * (_FIXED + 4 * s * _BORDER) + F.greatest(F.lit(0), F.max("load_u") * 8 - F.sum("load_u"))).cast("bigint").alias("time_u")).select(F.lit(c).alias("cells"), F.lit(s).alias("side"), "time_u")
        out = row if out is None else out.unionByName(row)
    return out


query("exp_tile_sweep", _sweep_sql())(sweep_rows)
query("m_best_tile_side", f"SELECT cells, min_by(side, time_u * 100 + side) AS side FROM ({_sweep_sql()}) GROUP BY cells")(lambda s, d: sweep_rows(s, d).groupBy("cells").agg(F.min_by("side", F.col("time_u") * 100 + F.col("side")).alias("side")))
query("exp_strong_scaling", _SCALE_SQL)(scaling_rows)
_TABLE = ((128, 1, (16, 8)), (64, 2, (8, 8)), (32, 4, (8, 4)), (16, 8, (4, 4)), (8, 16, (4, 2)))


def _table_sql() -> str:
    parts = []
    for n, t, g in _TABLE:
        for name, scheme, every, light in (("no_tiles", "uniform", None, "FALSE"), ("tiles", "hilbert", 40, "NOT is_heavy")):
            held = _wake_sql(every, scheme, n, grid=g)
            source = "(SELECT *, tile_id AS curve_idx FROM held)" if scheme == "uniform" else "(SELECT held.*, cur.curve_idx FROM held JOIN lat USING (step, tile_id) JOIN cur USING (tx, ty))"
            parts.append(f"SELECT * FROM ({twins.with_(held, _marked(t, source), _schedule(t, light))} SELECT {n} AS n_pe, {t} AS threads, '{name}' AS variant, CAST(sum(m) AS DOUBLE) / {t} AS time_u FROM (SELECT step, max(time_t) AS m FROM tim GROUP BY step))")
    return f"SELECT n_pe, threads, variant, round(time_u / min(time_u) OVER (), 4) AS time_norm FROM ({' UNION ALL '.join(parts)})"


@query("exp_wake_table", _table_sql())
def _(spark, d):
    from .. import curves, rebalance

    base, v, out = load_of(spark, d, "w9"), W["w9"], None
    for n, t, g in _TABLE:
        for name, scheme, every, mode in (("no_tiles", "uniform", None, "no_tiles"), ("tiles", "hilbert", 40, "hybrid")):
            held = rebalance.run(base, lambda x, n=n, g=g, c=scheme: decomp.decompose(x, v.dom, n, c, g), every)
            held = held.withColumn("curve_idx", F.col("tile_id") if scheme == "uniform" else curves.hilbert_index(v.dom))
            steps = metrics.core_load(threads.pe_time(held, t, mode))
            row = steps.agg((F.sum("core_t") / t).alias("time_u")).withColumns({"n_pe": F.lit(n), "threads": F.lit(t), "variant": F.lit(name)})
            out = row if out is None else out.unionByName(row)
    return out.select("n_pe", "threads", "variant", F.round(F.col("time_u") / F.min("time_u").over(Window.partitionBy()), 4).alias("time_norm"))


#: Runs of the wake by scheme and interval, with the cost of borders and of migration; each sampled step stands for 20.
_RUNS = (("uniform", None), ("hilbert", None), ("hilbert", 80), ("hilbert", 40), ("hilbert", 20))


def _run_sql() -> str:
    v, c, t, parts = W["w9"], cost.Cost(), 4, []
    nx, ny = v.dom.tiles
    faces = f"fac AS (SELECT step, 0 AS axis, tile_id AS a, (tx + 1) % {nx} + ty * {nx} AS b, {v.dom.tile[1]} AS cells FROM lat UNION ALL SELECT step, 1, tile_id, tx + ((ty + 1) % {ny}) * {nx}, {v.dom.tile[0]} FROM lat)"
    for scheme, every in _RUNS:
        source = "(SELECT *, tile_id AS curve_idx FROM held)" if scheme == "uniform" else "(SELECT held.*, cur.curve_idx FROM held JOIN lat USING (step, tile_id) JOIN cur USING (tx, ty))"
        moved = f"a.step % {every} = 0 AND b.step = a.step - {every}" if every else "FALSE"
        own = twins.with_(
            _wake_sql(every, scheme), _marked(t, source), _schedule(t, "NOT is_heavy"), faces,
            "ext AS (SELECT fac.step, axis, cells, x.pe AS a_pe, y.pe AS b_pe FROM fac JOIN held x ON x.step = fac.step AND x.tile_id = a JOIN held y ON y.step = fac.step AND y.tile_id = b WHERE x.pe <> y.pe)",
            "snd AS (SELECT step, axis, a_pe AS pe, b_pe AS o, cells FROM ext UNION ALL SELECT step, axis, b_pe, a_pe, cells FROM ext)",
            f"com AS (SELECT step, pe, count(DISTINCT axis * 100000 + o) * {c.latency} + sum(cells) * {c.per_cell} AS u FROM snd GROUP BY ALL)",
            f"mov AS (SELECT a.step, b.pe AS src, a.pe AS dst, a.n_part, a.n_cells FROM asg a JOIN asg b ON a.tile_id = b.tile_id AND a.pe <> b.pe AND {moved})",
            f"mig AS (SELECT step, src, count(DISTINCT dst) * {c.latency} + sum(n_part) * {c.migrate_part} + sum(n_cells) * {c.migrate_cell} AS u FROM mov GROUP BY ALL)",
            f"stp AS (SELECT tim.step, max(time_t) AS w, max(time_t + coalesce(u, 0) * {t}) AS s FROM tim LEFT JOIN com USING (step, pe) GROUP BY ALL)",
        )
        late = f"100 * {t} * coalesce((SELECT sum(m) FROM (SELECT max(u) AS m FROM mig GROUP BY step)), 0)"
        parts.append(f"SELECT * FROM ({own} SELECT '{scheme}' AS scheme, {every or 0} AS every, CAST(sum(w) * 2000 AS BIGINT) AS work_t, CAST({late} AS BIGINT) AS migrate_t, CAST(sum(s) * 2000 + {late} AS BIGINT) AS time_t FROM stp)")
    return " UNION ALL ".join(parts)


@query("exp_wake_run_time", _run_sql())
def _(spark, d):
    """Modelled time of whole runs: the slowest group's work alone (work_t), what migration adds, and all with borders (time_t)."""
    from .. import curves, exchange, rebalance

    base, v, t, out = load_of(spark, d, "w9"), W["w9"], 4, None
    edges = exchange.tile_edges(spark, v.dom)
    for scheme, every in _RUNS:
        make = lambda x, c=scheme: decomp.decompose(x, v.dom, v.n_pe, c, v.grid)
        held = rebalance.run(base, make, every).withColumn("curve_idx", F.col("tile_id") if scheme == "uniform" else curves.hilbert_index(v.dom))
        times = threads.pe_time(held, t)
        steps = cost.step_time(times, t, cost.border_cost(exchange.classify_edges(edges, held), v.dom))
        moved = cost.migration_cost(rebalance.migration(make(base.where(F.col("step") % every == 0)), every)) if every else spark.createDataFrame([], "step int, migrate_u bigint")
        work = cost.run_time(cost.step_time(times, t), t, repeat=20).select(F.col("time_t").alias("work_t"))
        row = cost.run_time(steps, t, moved, 20).crossJoin(F.broadcast(work)).crossJoin(F.broadcast(moved.agg((F.coalesce(F.sum("migrate_u"), F.lit(0)) * (100 * t)).alias("migrate_t"))))
        row = row.select(F.lit(scheme).alias("scheme"), F.lit(every or 0).alias("every"), "work_t", "migrate_t", "time_t")
        out = row if out is None else out.unionByName(row)
    return out


query("exp_ball_small_tiles"," UNION ALL ".join(f"SELECT '{k}' AS view, * FROM ({twins.with_(_repaired(W[k], 256))} {twins.IMBALANCE.format(n=256, asg='asg')})" for k in ("w6", "w6b")))(
    lambda s, d: metrics.imbalance(assigned(s, d, "w6", "hilbert", 256, (4, 8, 8), nonempty=True), 256).withColumn("view", F.lit("w6")).unionByName(metrics.imbalance(assigned(s, d, "w6b", "hilbert", 256, (4, 8, 8), nonempty=True), 256).withColumn("view", F.lit("w6b")))
)
