"""Decomposition schemes: from a load array to the group ("pe") of each tile."""

from __future__ import annotations

from math import prod

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import curves, cuts
from .lattice import Domain


def factors(n: int, shape: tuple[int, ...]) -> tuple[int, ...]:
    """n as a product of one factor an axis, as near to the proportions of shape as there is."""
    best: tuple[float, tuple[int, ...]] | None = None

    def visit(left: int, axis: int, got: tuple[int, ...]) -> None:
        nonlocal best
        if axis == len(shape) - 1:
            own = (*got, left)
            sides = [s / g for s, g in zip(shape, own)]
            cost = max(sides) / min(sides)
            if best is None or (cost, own) < best:
                best = (cost, own)
            return
        for g in range(1, left + 1):
            if left % g == 0:
                visit(left // g, axis + 1, (*got, g))

    visit(n, 0, ())
    assert best is not None
    return best[1]


def _axis_cut(load: DataFrame, keys: list[str], t: str, n: Column | int, out: str) -> DataFrame:
    """Cut the projection of load on axis t, separately for each key."""
    line = load.groupBy(*keys, t).agg(F.sum("load_u").alias("load_u"))
    return cuts.cut_prefix(line, n, by=tuple(keys), index=t, out=out).select(*keys, t, out)


def _jagged(load: DataFrame, dom: Domain, grid: tuple[Column | int, ...], by: tuple[str, ...]) -> DataFrame:
    """Stripes along x, each cut by itself along y, each part along z."""
    keys, pe = list(by), F.lit(0)
    for t, n in zip(dom.tcols, grid):
        part = f"_part_{t}"
        load = load.join(_axis_cut(load, keys, t, n, part), [*keys, t])
        keys.append(part)
        pe = pe * n + F.col(part)
    return load.withColumn("pe", pe.cast("int"))


def _rectilinear(load: DataFrame, dom: Domain, grid: tuple[Column | int, ...], by: tuple[str, ...]) -> DataFrame:
    """Every axis cut by its projection of the whole domain, so corners match."""
    pe, out = F.lit(0), load
    for t, n in zip(dom.tcols, grid):
        part = f"_part_{t}"
        out = out.join(_axis_cut(load, list(by), t, n, part), [*by, t])
        pe = pe * n + F.col(part)
    return out.withColumn("pe", pe.cast("int"))


def _refined(load: DataFrame, dom: Domain, grid: tuple[int, ...], by: tuple[str, ...], rounds: int) -> DataFrame:
    """Matching corners, improved: axes in turn are cut by the load that weighs most among the stripes of the others, not by their sum."""
    out = _rectilinear(load, dom, grid, by)
    parts = [f"_part_{t}" for t in dom.tcols]
    for k in range(rounds):
        a = k % dom.dims
        others = [p for i, p in enumerate(parts) if i != a]
        stripes = out.groupBy(*by, dom.tcols[a], *others).agg(F.sum("load_u").alias("load_u"))
        worst = stripes.groupBy(*by, dom.tcols[a]).agg(F.max("load_u").alias("load_u"))
        new = cuts.cut_prefix(worst, grid[a], by=by, index=dom.tcols[a], out="_new").select(*by, dom.tcols[a], "_new")
        out = out.join(new, [*by, dom.tcols[a]]).drop(parts[a]).withColumnRenamed("_new", parts[a])
    pe = F.lit(0)
    for p, n in zip(parts, grid):
        pe = pe * n + F.col(p)
    return out.withColumn("pe", pe.cast("int"))


def uniform(dom: Domain, grid: tuple[int | str, ...]) -> Column:
    """Equal boxes; grid is a number or an SQL expression for each axis."""
    pe = F.lit(0)
    for t, n, g in zip(dom.tcols, dom.tiles, grid):
        pe = pe * F.expr(str(g)) + F.expr(f"{t} * {g} div {n}")
    return pe.cast("int")


def ordered(load: DataFrame, dom: Domain, curve: str, by: tuple[str, ...] = ("step",)) -> DataFrame:
    return curves.by_load(load, by) if curve == "by_load" else load.withColumn("curve_idx", curves.INDEX[curve](dom))


def decompose(load: DataFrame, dom: Domain, n_pe: int, scheme: str, grid: tuple[int, ...] | None = None, by: tuple[str, ...] = ("step",), nonempty: bool = False, rounds: int = 4) -> DataFrame:
    """load with pe (and curve_idx for curves).  Each map is made from scratch: no earlier one is looked at.

    Schemes: uniform, one_axis, rectilinear, rectilinear_refined, jagged (in
    three dimensions too; axis_projection is its other name), row_major, snake,
    hilbert, by_load, greedy_<curve>, adaptive_<curve>.
    """
    grid = grid or factors(n_pe, dom.tiles)
    if prod(grid) != n_pe and scheme in ("uniform", "rectilinear", "rectilinear_refined", "jagged", "axis_projection"):
        raise ValueError(f"a grid of {grid} is not {n_pe} groups")
    if n_pe < 1 or n_pe > dom.n_tiles:
        raise ValueError(f"{n_pe} groups of {dom.n_tiles} tiles")
    if scheme == "uniform":
        return load.withColumn("pe", uniform(dom, grid))
    if scheme == "one_axis":
        return load.join(_axis_cut(load, list(by), "tx", n_pe, "pe"), [*by, "tx"])
    if scheme == "rectilinear":
        return _rectilinear(load, dom, grid, by)
    if scheme == "rectilinear_refined":
        return _refined(load, dom, grid, by, rounds)
    if scheme in ("jagged", "axis_projection"):
        return _jagged(load, dom, grid, by)
    kind, _, curve = scheme.rpartition("_") if scheme.startswith(("greedy_", "adaptive_")) else ("", "", scheme)
    line = ordered(load, dom, curve, by)
    if kind:
        return cuts.cut_greedy(line, n_pe, "fixed" if kind == "greedy" else "adaptive", by)
    cut = cuts.cut_prefix(line, n_pe, by)
    return cuts.ensure_nonempty(line, cut, n_pe, by) if nonempty else cut


def decompose_each(load: DataFrame, dom: Domain, counts: tuple[int, ...], scheme: str, by: tuple[str, ...] = ("step",), nonempty: bool = False) -> DataFrame:
    """load with n_pe and pe, once for each number of groups in counts.  All maps are one plan: n_pe is one more key of the windows, so the tiles are counted and shuffled once.  Schemes: uniform, rectilinear, jagged, row_major, snake, hilbert, by_load."""
    if not counts or min(counts) < 1 or max(counts) > dom.n_tiles:
        raise ValueError(f"{counts} groups of {dom.n_tiles} tiles")
    keys = (*by, "n_pe")
    boxes = scheme in ("uniform", "rectilinear", "jagged")
    many = (load if boxes else ordered(load, dom, scheme, by)).withColumn("n_pe", F.explode(F.array(*[F.lit(n) for n in counts])))
    sides = zip(*[factors(n, dom.tiles) for n in counts])
    grid = tuple(f"element_at(map({', '.join(f'{n}, {g}' for n, g in zip(counts, axis))}), n_pe)" for axis in sides)
    if scheme == "uniform":
        return many.withColumn("pe", uniform(dom, grid))
    if boxes:
        cut = _jagged if scheme == "jagged" else _rectilinear
        return cut(many, dom, tuple(map(F.expr, grid)), keys)
    cut = cuts.cut_prefix(many, F.col("n_pe"), keys)
    return cuts.ensure_nonempty(many, cut, F.col("n_pe"), keys) if nonempty else cut


def place(df: DataFrame, n_pe: int) -> DataFrame:
    """Rows with pe k in partition k."""
    return df.repartitionById(n_pe, F.col("pe"))


def components(assigned: DataFrame, edges: DataFrame, by: tuple[str, ...] = ("step",), rounds: int = 200) -> DataFrame:
    """Connected regions of each pe over tile faces: by, pe, n_regions.  Labels are smallest tile ids, spread with pointer jumping; lineage is cut by checkpoint().  Labels that still move after `rounds` are an error."""
    own = assigned.select(*by, "tile_id", "pe")
    a, b = own.select(*by, F.col("tile_id").alias("a_tile"), "pe"), own.select(*by, F.col("tile_id").alias("b_tile"), "pe")
    links = edges.select("a_tile", "b_tile").join(a, "a_tile").join(b, [*by, "b_tile", "pe"])
    both = links.select(*by, "a_tile", "b_tile").unionByName(links.select(*by, F.col("b_tile").alias("a_tile"), F.col("a_tile").alias("b_tile"))).distinct().checkpoint()
    labels = own.withColumn("root", F.col("tile_id"))
    for _ in range(rounds):
        near = both.join(labels.select(*by, F.col("tile_id").alias("b_tile"), "root"), [*by, "b_tile"]).groupBy(*by, F.col("a_tile").alias("tile_id")).agg(F.min("root").alias("near"))
        hooked = labels.join(near, [*by, "tile_id"], "left").withColumn("new", F.least("root", F.coalesce("near", "root")))
        far = labels.select(*by, F.col("tile_id").alias("new"), F.col("root").alias("far"))
        nxt = hooked.join(far, [*by, "new"]).select(*by, "tile_id", "pe", F.least("new", "far").alias("root"), (F.least("new", "far") < F.col("root")).alias("moved")).checkpoint()
        labels = nxt.drop("moved")
        if nxt.where("moved").isEmpty():
            return labels.groupBy(*by, "pe").agg(F.countDistinct("root").alias("n_regions"))
    raise RuntimeError(f"labels still move after {rounds} rounds")
