"""Strong scaling of the ball: six lines over six core counts, each tiled one with its best number of threads.

All configurations of a line are one plan: the number of groups and the number
of threads are keys beside the step.  Borders cost what the cost model's default weights
say, in load units (a border cell a quarter of what its push costs in this view).
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .. import cost, decomp, exchange, threads
from ..views import VIEWS as W
from . import query, twins
from .balance import load_of
from .work import _safe as safe

VIEW, CORES, THREADS = W["w6"], (8, 16, 32, 64, 128, 256), (2, 4, 8, 16)
#: Line -> scheme, mode.  Lines without tiles take all threads there are, 16 at most.
LINES = {
    "no balancing": ("uniform", "no_tiles"), "previous balancing": ("rectilinear", "no_tiles"), "light tiles": ("hilbert", "light_only"),
    "hybrid hilbert": ("hilbert", "hybrid"), "hybrid snake": ("snake", "hybrid"), "hybrid jagged": ("jagged", "hybrid"),
}
TILED = tuple((c // t, t) for c in CORES for t in THREADS if t <= c)
WHOLE = tuple((max(1, c // THREADS[-1]), min(c, THREADS[-1])) for c in CORES)
WEIGHTS = cost.Cost()


def _groups(pairs) -> tuple[int, ...]:
    return tuple(sorted({n for n, _ in pairs}))


def _threads(pairs):
    """The thread counts that go with a row's n_pe, exploded."""
    text = ", ".join(f"{n}, array({', '.join(str(t) for m, t in pairs if m == n)})" for n in _groups(pairs))
    return F.explode(F.expr(f"element_at(map({text}), n_pe)"))


def line_times(load: DataFrame, dom, edges: DataFrame) -> DataFrame:
    """line, cores, threads, work_u and time_u (the slowest group's load a thread without and with borders, over all steps), heavy (share of heavy tiles).

    Maps and loads (rows are tiles) are written once, by checkpoint(), as several plans read them.
    """
    load, maps = load.checkpoint(), []
    for scheme in sorted({scheme for scheme, _ in LINES.values()}):
        pairs = TILED if scheme in ("hilbert", "snake", "jagged") else WHOLE
        held = decomp.decompose_each(load, dom, _groups(pairs), scheme, nonempty=scheme in ("hilbert", "snake"))
        index = F.col("curve_idx" if "curve_idx" in held.columns else "tile_id").alias("curve_idx")
        maps.append(held.select(F.lit(scheme).alias("scheme"), "step", "n_pe", "tile_id", "n_cells", "load_u", index, "pe"))
    held, at = reduce(DataFrame.unionByName, maps).checkpoint(), ("scheme", "step", "n_pe")
    borders = cost.border_cost(exchange.classify_edges(edges, held, at), dom, WEIGHTS, at)
    keys, out = (*at, "threads"), None
    for mode in sorted({mode for _, mode in LINES.values()}):
        pairs = WHOLE if mode == "no_tiles" else TILED
        lines = F.create_map(*[F.lit(x) for line, (scheme, m) in LINES.items() if m == mode for x in (scheme, line)])
        own = held.withColumn("scheme", F.element_at(lines, F.col("scheme"))).where("scheme IS NOT NULL").withColumn("threads", _threads(pairs))
        times = threads.pe_time(own, F.col("threads"), mode, keys).withColumn("n_heavy", F.col("n_heavy") if mode == "hybrid" else F.lit(0).cast("bigint"))
        sent = borders.withColumn("scheme", F.element_at(lines, F.col("scheme"))).where("scheme IS NOT NULL").withColumn("threads", _threads(pairs))
        slow = cost.step_time(times, F.col("threads"), sent, WEIGHTS, keys).withColumnRenamed("time_t", "all_t")
        work = times.groupBy(*keys).agg(F.max("time_t").alias("work_t"), F.sum("n_heavy").alias("n_heavy"), F.sum("n_tiles").alias("n_tiles"))
        row = work.join(slow, list(keys))
        out = row if out is None else out.unionByName(row)
    both = out.groupBy(F.col("scheme").alias("line"), "n_pe", "threads").agg(F.sum("work_t").alias("w"), F.sum("all_t").alias("a"), F.sum("n_heavy").alias("h"), F.sum("n_tiles").alias("m"))
    return both.select("line", (F.col("n_pe") * F.col("threads")).alias("cores"), "threads", (F.col("w") / F.col("threads")).alias("work_u"), (F.col("a") / (F.col("threads") * 100)).alias("time_u"), (F.col("h") / F.col("m")).alias("heavy"))


def scaling_lines(spark, d: str) -> DataFrame:
    """Of each line and core count the configuration with the least time (of equal ones that with fewer threads)."""
    safe(spark)
    every = line_times(load_of(spark, d, "w6"), VIEW.dom, exchange.tile_edges(spark, VIEW.dom))
    best = every.groupBy("line", "cores").agg(F.min(F.struct("time_u", "threads", "work_u", "heavy")).alias("b"))
    return best.select("line", "cores", "b.threads", "b.work_u", "b.time_u", F.round("b.heavy", 6).alias("heavy"))


def _cut(source: str, keys: str, index: str, n: str, out: str, name: str) -> str:
    """name: source's rows with `out` by the midpoint rule; n is an expression of a row."""
    total = f"sum(load_u) OVER (PARTITION BY {keys})"
    cum = f"sum(load_u) OVER (PARTITION BY {keys} ORDER BY {index} ROWS UNBOUNDED PRECEDING)"
    return f"{name} AS (SELECT *, CAST(least(CAST((2 * {cum} - load_u) * {n} AS HUGEINT) // CAST(2 * {total} AS HUGEINT), {n} - 1) AS INTEGER) AS {out} FROM {source})"


def _maps_sql() -> str:
    """CTEs up to held(line, tiled, step, n_pe, tile_id, tx.., load_u, curve_idx, pe)."""
    dom, t = VIEW.dom, VIEW.dom.tcols
    grids = ", ".join(str((n, *decomp.factors(n, dom.tiles))) for n in _groups(TILED + WHOLE))
    parts = [twins.load(VIEW), f"gr(n_pe, g_tx, g_ty, g_tz) AS (VALUES {grids})", "many AS (SELECT * FROM load CROSS JOIN gr)"]
    shares = []
    for kind in ("hilbert", "snake"):
        k, n = kind[0], dom.n_tiles
        parts += [
            twins.curve(dom, kind, f"{k}_cur"),
            f"{k}_line AS (SELECT many.*, curve_idx FROM many JOIN {k}_cur USING ({', '.join(t)}))",
            _cut(f"{k}_line", "step, n_pe", "curve_idx", "n_pe", "pe", f"{k}_raw"),
            f"{k}_cnt AS (SELECT step, n_pe, k, (SELECT count(*) FROM {k}_raw r WHERE r.step = s.step AND r.n_pe = s.n_pe AND r.pe < k) AS c FROM (SELECT DISTINCT step, n_pe FROM {k}_raw) s, LATERAL (SELECT unnest(range(s.n_pe)) AS k))",
            f"{k}_fix AS (SELECT step, n_pe, k, least(k + max(c - k) OVER (PARTITION BY step, n_pe ORDER BY k), {n} - (n_pe - k)) AS c FROM {k}_cnt)",
            f"{k}_asg AS (SELECT r.* EXCLUDE (pe), CAST(e.k AS INTEGER) AS pe FROM {k}_raw r ASOF JOIN {k}_fix e ON e.step = r.step AND e.n_pe = r.n_pe AND r.curve_idx >= e.c)",
        ]
    for kind in ("jagged", "rectilinear"):
        src, keys, k = "many", ["step", "n_pe"], kind[0]
        for c in t:
            base = src if kind == "jagged" else "many"
            parts += [
                f"{k}a_{c} AS (SELECT {', '.join(keys)}, any_value(g_{c}) AS g, {c}, sum(load_u) AS load_u FROM {base} GROUP BY {', '.join(keys)}, {c})",
                _cut(f"{k}a_{c}", ", ".join(keys), c, "g", f"p_{c}", f"{k}b_{c}"),
                f"{k}c_{c} AS (SELECT a.*, b.p_{c} FROM {src} a JOIN (SELECT * EXCLUDE (load_u, g) FROM {k}b_{c}) b USING ({', '.join([*keys, c])}))",
            ]
            src, keys = f"{k}c_{c}", [*keys, f"p_{c}"] if kind == "jagged" else keys
        parts.append(f"{k}_asg AS (SELECT *, CAST((p_tx * g_ty + p_ty) * g_tz + p_tz AS INTEGER) AS pe FROM {src})")
    n = dom.tiles
    parts.append(f"u_asg AS (SELECT *, CAST(((tx * g_tx // {n[0]}) * g_ty + (ty * g_ty // {n[1]})) * g_tz + (tz * g_tz // {n[2]}) AS INTEGER) AS pe FROM many)")
    for line, (scheme, mode) in LINES.items():
        index = "curve_idx" if scheme in ("hilbert", "snake") else "tile_id"
        shares.append(f"SELECT '{line}' AS line, '{mode}' AS mode, step, n_pe, tile_id, {', '.join(t)}, load_u, {index} AS curve_idx, pe FROM {scheme[0]}_asg")
    return ", ".join([*parts, f"held AS ({' UNION ALL '.join(shares)})"])


def _lines_sql() -> str:
    dom = VIEW.dom
    pairs = ", ".join(f"('{m}', {n}, {t})" for m in ("no_tiles", "light_only", "hybrid") for n, t in (WHOLE if m == "no_tiles" else TILED))
    faces = []
    for a, c in enumerate(dom.tcols):
        near = " AND ".join(f"y.{o} = " + (f"(x.{o} + 1) % {n}" if o == c else f"x.{o}") for o, n in zip(dom.tcols, dom.tiles))
        faces.append(f"SELECT x.line, x.step, x.n_pe, {a} AS axis, x.pe AS a, y.pe AS b, {dom.cells_per_tile // dom.tile[a]} AS cells FROM held x JOIN held y ON y.line = x.line AND y.step = x.step AND y.n_pe = x.n_pe AND {near} WHERE x.pe <> y.pe")
    least = "list_reduce(l, lambda acc, x: list_transform(acc, lambda c, i: CASE WHEN i = list_position(acc, list_min(acc)) THEN c + x[1] ELSE c END), list_transform(range(threads), lambda z: CAST(0 AS BIGINT)))"
    return twins.with_(
        _maps_sql(),
        f"cfg(mode, n_pe, threads) AS (VALUES {pairs})",
        "cls AS (SELECT *, load_u * threads >= sum(load_u) OVER g OR count(*) OVER g < threads AS heavy FROM held JOIN cfg USING (mode, n_pe) WINDOW g AS (PARTITION BY line, step, n_pe, threads, pe))",
        "grp AS (SELECT line, mode, step, n_pe, threads, pe, list([load_u] ORDER BY curve_idx) FILTER (mode = 'light_only' OR mode = 'hybrid' AND NOT heavy) AS l, "
        "coalesce(sum(load_u) FILTER (mode = 'no_tiles' OR mode = 'hybrid' AND heavy), 0) AS shared, count(*) FILTER (heavy AND mode = 'hybrid') AS h, count(*) AS m FROM cls GROUP BY ALL)",
        f"tim AS (SELECT * EXCLUDE (l), CAST(coalesce(list_max({least}), 0) * threads + shared AS BIGINT) AS t FROM grp)",
        f"ext AS ({' UNION ALL '.join(faces)})",
        "snd AS (SELECT line, step, n_pe, axis, a AS pe, b AS o, cells FROM ext UNION ALL SELECT line, step, n_pe, axis, b, a, cells FROM ext)",
        f"com AS (SELECT line, step, n_pe, pe, count(DISTINCT axis * 100000 + o) * {WEIGHTS.latency} + sum(cells) * {WEIGHTS.per_cell} AS u FROM snd GROUP BY ALL)",
        "stp AS (SELECT line, step, n_pe, threads, max(t) AS w, max(t + coalesce(u, 0) * threads) AS a, sum(h) AS h, sum(m) AS m FROM tim LEFT JOIN com USING (line, step, n_pe, pe) GROUP BY ALL)",
        "run AS (SELECT line, CAST(n_pe * threads AS INTEGER) AS cores, threads, CAST(sum(w) AS DOUBLE) / threads AS work_u, CAST(sum(a) AS DOUBLE) / threads AS time_u, round(CAST(sum(h) AS DOUBLE) / sum(m), 6) AS heavy FROM stp GROUP BY line, n_pe, threads)",
    ) + "SELECT * FROM run QUALIFY row_number() OVER (PARTITION BY line, cores ORDER BY time_u, threads) = 1"


_SQL = _lines_sql()
query("exp_scaling_lines", _SQL)(scaling_lines)
#: Performance beside the fastest line at the fewest cores, and the same of the largest load of a core.
query("m_scaling_lines", f"SELECT line, cores, round(f / time_u, 4) AS performance, round(g / work_u, 4) AS balance FROM ({_SQL}), (SELECT min(time_u) AS f, min(work_u) AS g FROM ({_SQL}) WHERE cores = {CORES[0]})")(
    lambda s, d: scaling_lines(s, d)
    .withColumn("f", F.min(F.when(F.col("cores") == CORES[0], F.col("time_u"))).over(Window.partitionBy()))
    .withColumn("g", F.min(F.when(F.col("cores") == CORES[0], F.col("work_u"))).over(Window.partitionBy()))
    .select("line", "cores", F.round(F.col("f") / F.col("time_u"), 4).alias("performance"), F.round(F.col("g") / F.col("work_u"), 4).alias("balance"))
)
