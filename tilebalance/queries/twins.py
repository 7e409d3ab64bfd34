"""SQL building blocks of the twins, written independently of the DataFrame code: curves grow forward from copies of themselves."""

from __future__ import annotations

from ..curves import COPIES, OCTANTS
from ..lattice import Domain
from ..views import View


def particles(v: View) -> str:
    return f"p AS ({v.sql()})"


def lattice(dom: Domain, steps: str | None = "SELECT DISTINCT step FROM p") -> str:
    """lat: [step,] tile_id, tx.."""
    froms = ", ".join(f"generate_series(0, {n - 1}) g{t}({t})" for t, n in zip(dom.tcols, dom.tiles))
    ident, mult = [], 1
    for t, n in zip(dom.tcols, dom.tiles):
        ident.append(f"{t} * {mult}")
        mult *= n
    head = f"FROM ({steps}) s, {froms}" if steps else f"FROM {froms}"
    return f"lat AS (SELECT {'s.step, ' if steps else ''}CAST({' + '.join(ident)} AS BIGINT) AS tile_id, {', '.join(f'CAST({t} AS INTEGER) AS {t}' for t in dom.tcols)} {head})"


def load(v: View, weight: tuple[int, int] | None = None) -> str:
    """CTEs p, lat, load(step, tile_id, tx.., n_part, n_cells, load_u)."""
    num, den = weight or v.weight
    dom = v.dom
    binned = ", ".join(f"{c} // {s} AS {t}" for t, c, s in zip(dom.tcols, dom.ccols, dom.tile))
    keys = ", ".join(dom.tcols)
    return (
        f"{particles(v)}, {lattice(dom)}, cnt AS (SELECT step, {binned}, count(*) AS n FROM p GROUP BY ALL), "
        f"load AS (SELECT step, tile_id, {keys}, coalesce(n, 0) AS n_part, CAST({dom.cells_per_tile} AS BIGINT) AS n_cells, CAST({den} * coalesce(n, 0) + {num * dom.cells_per_tile} AS BIGINT) AS load_u FROM lat LEFT JOIN cnt USING (step, {keys}))"
    )


def hilbert2(dom: Domain, name: str = "cur") -> str:
    """name(tx, ty, curve_idx), grown quadrant by quadrant; blocks chained along the longer axis."""
    nx, ny = dom.tiles
    side, long = min(nx, ny), max(nx, ny)
    k = side.bit_length() - 1
    a, b = ("x", "y") if nx >= ny else ("y", "x")
    return (
        f"{name}_g AS (SELECT 0 AS lvl, 0 AS x, 0 AS y, 0 AS d UNION ALL SELECT lvl + 1, "
        "CASE q WHEN 0 THEN y WHEN 1 THEN x WHEN 2 THEN x + (1 << lvl) ELSE 2 * (1 << lvl) - 1 - y END, "
        "CASE q WHEN 0 THEN x WHEN 1 THEN y + (1 << lvl) WHEN 2 THEN y + (1 << lvl) ELSE (1 << lvl) - 1 - x END, "
        f"d + q * (1 << lvl) * (1 << lvl) FROM {name}_g, generate_series(0, 3) gq(q) WHERE lvl < {k}), "
        f"{name} AS (SELECT CAST({'x + blk * ' + str(side) if a == 'x' else 'y'} AS INTEGER) AS tx, CAST({'y' if a == 'x' else 'x + blk * ' + str(side)} AS INTEGER) AS ty, CAST(d + blk * {side * side} AS BIGINT) AS curve_idx "
        f"FROM {name}_g, generate_series(0, {long // side - 1}) gb(blk) WHERE lvl = {k})"
    )


def hilbert3(dom: Domain, name: str = "cur") -> str:
    """name(tx, ty, tz, curve_idx) of a cube, grown octant by octant."""
    k = dom.tiles[0].bit_length() - 1
    v, cols = ("x", "y", "z"), []
    for j in range(3):
        whens = []
        for o, (octant, (perm, flip)) in enumerate(zip(OCTANTS, COPIES)):
            own = f"(1 << lvl) - 1 - {v[perm[j]]}" if flip[j] else v[perm[j]]
            whens.append(f"WHEN {o} THEN {own}" + (" + (1 << lvl)" if octant[j] else ""))
        cols.append(f"CASE q {' '.join(whens)} END")
    return (
        f"{name}_g AS (SELECT 0 AS lvl, 0 AS x, 0 AS y, 0 AS z, 0 AS d UNION ALL SELECT lvl + 1, {', '.join(cols)}, d + q * (1 << (3 * lvl)) FROM {name}_g, generate_series(0, 7) gq(q) WHERE lvl < {k}), "
        f"{name} AS (SELECT CAST(x AS INTEGER) AS tx, CAST(y AS INTEGER) AS ty, CAST(z AS INTEGER) AS tz, CAST(d AS BIGINT) AS curve_idx FROM {name}_g WHERE lvl = {k})"
    )


def snake(dom: Domain, name: str = "cur") -> str:
    """name(tx.., curve_idx) by ranking rows, then tiles in rows."""
    n = dom.tiles
    if dom.dims == 2:
        return f"{name} AS (SELECT CAST(tx AS INTEGER) AS tx, CAST(ty AS INTEGER) AS ty, row_number() OVER (ORDER BY ty, CASE WHEN ty % 2 = 0 THEN tx ELSE -tx END) - 1 AS curve_idx FROM generate_series(0, {n[0] - 1}) a(tx), generate_series(0, {n[1] - 1}) b(ty))"
    return (
        f"{name}_r AS (SELECT ty, tz, row_number() OVER (ORDER BY tz, CASE WHEN tz % 2 = 0 THEN ty ELSE -ty END) - 1 AS r FROM generate_series(0, {n[1] - 1}) b(ty), generate_series(0, {n[2] - 1}) c(tz)), "
        f"{name} AS (SELECT CAST(tx AS INTEGER) AS tx, CAST(ty AS INTEGER) AS ty, CAST(tz AS INTEGER) AS tz, row_number() OVER (ORDER BY r, CASE WHEN r % 2 = 0 THEN tx ELSE -tx END) - 1 AS curve_idx FROM {name}_r, generate_series(0, {n[0] - 1}) a(tx))"
    )


def curve(dom: Domain, kind: str, name: str = "cur") -> str:
    if kind == "row_major":
        return f"{name} AS (SELECT {', '.join(dom.tcols)}, tile_id AS curve_idx FROM lat GROUP BY ALL)"
    return snake(dom, name) if kind == "snake" else (hilbert2 if dom.dims == 2 else hilbert3)(dom, name)


def prefix(source: str, keys: list[str], index: str, n: int, out: str, name: str, extra: str = "") -> str:
    """name: rows of source with `out`, by the midpoint rule on windows over exact numbers."""
    part = f"PARTITION BY {', '.join(keys)}" if keys else ""
    total = f"sum(load_u) OVER ({part})"
    cum = f"sum(load_u) OVER ({part} ORDER BY {index} ROWS UNBOUNDED PRECEDING)"
    at = f"(row_number() OVER ({part} ORDER BY {index}) - 1)"
    return (
        f"{name} AS (SELECT *{extra}, CAST(least(CASE WHEN {total} > 0 THEN CAST((2 * {cum} - load_u) * {n} AS HUGEINT) // nullif(CAST(2 * {total} AS HUGEINT), 0) "
        f"ELSE {at} * {n} // count(*) OVER ({part}) END, {n - 1}) AS INTEGER) AS {out} FROM {source})"
    )


def assign(v: View, scheme: str, n_pe: int | None = None, grid: tuple[int, ...] | None = None, weight: tuple[int, int] | None = None, loads: bool = True) -> str:
    """CTEs up to asg: load's columns and pe (and curve_idx for curves)."""
    dom, n, grid = v.dom, n_pe or v.n_pe, grid or v.grid
    head = [load(v, weight)] if loads else []
    t = dom.tcols
    if scheme == "uniform":
        pe = "0"
        for c, k, g in zip(t, dom.tiles, grid):
            pe = f"({pe}) * {g} + ({c} * {g} // {k})"
        return ", ".join([*head, f"asg AS (SELECT *, CAST({pe} AS INTEGER) AS pe FROM load)"])
    if scheme == "one_axis":
        line = "px AS (SELECT step, tx, sum(load_u) AS load_u FROM load GROUP BY ALL)"
        return ", ".join([*head, line, prefix("px", ["step"], "tx", n, "pe", "qx"), "asg AS (SELECT load.*, qx.pe FROM load JOIN qx USING (step, tx))"])
    if scheme in ("rectilinear", "jagged", "axis_projection"):
        parts, keys, src, pe = [], ["step"], "load", "0"
        for c, g in zip(t, grid):
            own = keys if scheme != "rectilinear" else ["step"]
            base = src if scheme != "rectilinear" else "load"
            parts += [f"j_{c} AS (SELECT {', '.join(own)}, {c}, sum(load_u) AS load_u FROM {base} GROUP BY ALL)", prefix(f"j_{c}", own, c, g, f"p_{c}", f"k_{c}"), f"l_{c} AS (SELECT a.*, b.p_{c} FROM {src} a JOIN (SELECT * EXCLUDE (load_u) FROM k_{c}) b USING ({', '.join([*own, c])}))"]
            src, keys, pe = f"l_{c}", [*keys, f"p_{c}"], f"({pe}) * {g} + p_{c}"
        return ", ".join([*head, *parts, f"asg AS (SELECT load.*, CAST({pe} AS INTEGER) AS pe FROM load JOIN (SELECT step, tile_id, {', '.join(f'p_{c}' for c in t)} FROM {src}) USING (step, tile_id))"])
    if scheme == "by_load":
        line = "line AS (SELECT *, row_number() OVER (PARTITION BY step ORDER BY load_u DESC, tile_id) - 1 AS curve_idx FROM load)"
        return ", ".join([*head, line, prefix("line", ["step"], "curve_idx", n, "pe", "asg")])
    kind, _, c = scheme.rpartition("_") if scheme.startswith(("greedy_", "adaptive_")) else ("", "", scheme)
    line = f"line AS (SELECT load.*, cur.curve_idx FROM load JOIN cur USING ({', '.join(t)}))"
    parts = [*head, curve(dom, c), line]
    if not kind:
        return ", ".join([*parts, prefix("line", ["step"], "curve_idx", n, "pe", "asg")])
    share, goal = (f"{n}", "total") if kind == "greedy" else (f"({n} - pe)", "(total - done)")
    fresh_share, fresh_goal = share, goal
    near = f"abs((s + l.load_u) * {fresh_share} - {fresh_goal}) < abs(s * {fresh_share} - {fresh_goal})"
    stay = f"(pe = {n - 1} OR ({near} AND m - g.curve_idx - 1 > {n - 1} - pe))"
    walk = (
        "tot AS (SELECT step, sum(load_u) AS total, count(*) AS m FROM line GROUP BY step), "
        "walk AS (SELECT step, curve_idx, 0 AS pe, CAST(load_u AS HUGEINT) AS s, CAST(0 AS HUGEINT) AS done FROM line WHERE curve_idx = 0 UNION ALL "
        f"SELECT g.step, l.curve_idx, CASE WHEN {stay} THEN pe ELSE pe + 1 END, CASE WHEN {stay} THEN s + l.load_u ELSE l.load_u END, CASE WHEN {stay} THEN done ELSE done + s END "
        "FROM walk g JOIN line l ON l.step = g.step AND l.curve_idx = g.curve_idx + 1 JOIN tot ON tot.step = g.step)"
    )
    return ", ".join([*parts, walk, "asg AS (SELECT line.*, CAST(walk.pe AS INTEGER) AS pe FROM line JOIN walk USING (step, curve_idx))"])


def with_(*parts: str) -> str:
    return "WITH RECURSIVE " + ", ".join(parts) + " "


IMBALANCE = "SELECT step, max(s) AS max_u, sum(s) AS total_u, round(CAST(max(s) * {n} AS DOUBLE) / sum(s), 6) AS imbalance FROM (SELECT step, pe, sum(load_u) AS s FROM {asg} GROUP BY ALL) GROUP BY step"
