"""A minimal particle-in-cell substrate: push, deposit, field, gather."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .lattice import Domain

MILLI = 1000


def push(particles: DataFrame, dom: Domain, steps: int = 1) -> DataFrame:
    """Free streaming in milli-cells: position plus velocity times steps, wrapped.  Needs x.., vx..; a projection."""
    return particles.withColumns({a: F.pmod(F.col(a) + F.col(f"v{a}") * steps, F.lit(n * MILLI)) for a, n in zip(dom.axes, dom.cells)})


def shape_weights(offset: Column, order: int) -> list[tuple[int, Column]]:
    """(cell offset, weight) of one axis; offset is the distance from the centre of the particle's cell, in cells."""
    if order == 0:
        return [(0, F.lit(1.0))]
    if order == 1:
        return [(-1, F.greatest(F.lit(0.0), -offset)), (0, 1 - F.abs(offset)), (1, F.greatest(F.lit(0.0), offset))]
    if order == 2:
        return [(-1, (0.5 - offset) * (0.5 - offset) / 2), (0, 0.75 - offset * offset), (1, (0.5 + offset) * (0.5 + offset) / 2)]
    raise ValueError("shape orders are 0 (nearest), 1 (linear) and 2 (quadratic)")


def _points(particles: DataFrame, dom: Domain, order: int, keep: list[str]) -> DataFrame:
    """One row for each particle and cell it touches: keep, cx.., w."""
    cell = {c: F.expr(f"cast({a} div {MILLI} as int)") for a, c in zip(dom.axes, dom.ccols)}
    out = particles.withColumns(cell).withColumn("w", F.lit(1.0))
    for a, c, n in zip(dom.axes, dom.ccols, dom.cells):
        offset = (F.col(a) % MILLI) / MILLI - 0.5
        terms = F.array(*[F.struct(F.pmod(F.col(c) + k, F.lit(n)).alias("c"), (F.col("w") * w).alias("w")) for k, w in shape_weights(offset, order)])
        out = out.withColumn("_p", F.explode(terms)).withColumns({c: F.col("_p.c"), "w": F.col("_p.w")}).drop("_p")
    return out.select(*keep, *dom.ccols, "w")


def deposit(particles: DataFrame, dom: Domain, order: int = 2, strategy: str = "private", slots: int = 4, by: tuple[str, ...] = ()) -> DataFrame:
    """Density on cells: by, cx.., value.

    private: every slot sums its own copy of the cells, copies are added up
    afterwards (a hot cell's rows are so dealt over slots tasks); atomic: one
    sum over all rows of a cell.
    """
    keep = list(by)
    if strategy == "atomic":
        return _points(particles, dom, order, keep).groupBy(*keep, *dom.ccols).agg(F.sum("w").alias("value"))
    if strategy != "private":
        raise ValueError("strategy is private or atomic")
    salted = particles.withColumn("_slot", F.pmod(F.xxhash64(*particles.columns), F.lit(slots)))
    partial = _points(salted, dom, order, [*keep, "_slot"]).groupBy(*keep, "_slot", *dom.ccols).agg(F.sum("w").alias("v"))
    return partial.groupBy(*keep, *dom.ccols).agg(F.sum("v").alias("value"))


def cell_mesh(spark, dom: Domain, value: Column | None = None) -> DataFrame:
    """Every cell with a value (0.0 by default)."""
    n, step, cols = 1, 1, {}
    for c in dom.cells:
        n *= c
    for c, k in zip(dom.ccols, dom.cells):
        cols[c] = F.expr(f"cast((id div {step}) % {k} as int)")
        step *= k
    return spark.range(n).select(*[v.alias(k) for k, v in cols.items()]).withColumn("value", value if value is not None else F.lit(0.0))


def field(density: DataFrame, dom: Domain, sweeps: int = 4) -> DataFrame:
    """A toy potential: Jacobi sweeps of the difference equation with the density as its source.  Neighbours come from an aggregation of shifted rows, no self-join; every few sweeps lineage is cut."""
    source = cell_mesh(density.sparkSession, dom).drop("value").join(density.select(*dom.ccols, "value"), dom.ccols, "left").withColumn("rho", F.coalesce("value", F.lit(0.0))).drop("value")
    mean = source.agg(F.avg("rho").alias("m"))
    source = source.crossJoin(F.broadcast(mean)).withColumn("rho", F.col("rho") - F.col("m")).drop("m")
    phi = source.select(*dom.ccols, F.lit(0.0).alias("value"))
    for k in range(sweeps):
        shifted = [phi.withColumn(c, F.pmod(F.col(c) + s, F.lit(n))) for c, n in zip(dom.ccols, dom.cells) for s in (-1, 1)]
        around = reduce(DataFrame.unionByName, shifted).groupBy(*dom.ccols).agg(F.sum("value").alias("s"))
        phi = source.join(around, dom.ccols).select(*dom.ccols, ((F.col("s") + F.col("rho")) / (2 * dom.dims)).alias("value"))
        if k % 4 == 3:
            phi = phi.checkpoint()
    return phi


def gather(particles: DataFrame, mesh: DataFrame, dom: Domain, order: int = 2, key: str = "pid") -> DataFrame:
    """Field at each particle, with the weights of the deposit: pid, field."""
    points = _points(particles, dom, order, [key])
    return points.join(mesh.select(*dom.ccols, "value"), dom.ccols).groupBy(key).agg(F.sum(F.col("w") * F.col("value")).alias("field"))
