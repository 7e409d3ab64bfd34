"""The load model: particles of a tile plus a weight for each of its cells, in exact integers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .lattice import Domain, bin_particles, lattice


def load_array(particles: DataFrame, dom: Domain, cell_weight: tuple[int, int] = (1, 1), by: tuple[str, ...] = ("step",), weight_col: str | None = None, formula: Column | None = None, steps: DataFrame | None = None) -> DataFrame:
    """by, tile_id, tx.., n_part, n_cells, load_u.

    cell_weight is a ratio (numerator, denominator): load_u = denominator *
    n_part + numerator * n_cells.  weight_col counts weights instead of
    particles; formula replaces the model by any expression of n_part and
    n_cells.  Particles are counted map-side, so at most one row for each tile
    and task is shuffled; the counts meet the lattice on the keys they were
    shuffled by, or by broadcast where Spark finds them small.  steps (rows of
    by) names the keys that get a lattice each, with or without particles; if it
    is not given they are learnt by a second scan of the particles.
    """
    num, den = cell_weight
    spark, keys = particles.sparkSession, list(by)
    amount = F.count("*") if weight_col is None else F.sum(weight_col).cast("bigint")
    counts = bin_particles(particles, dom).groupBy(*keys, "tile_id").agg(amount.alias("n_part"))
    tiles = lattice(spark, dom)
    if keys:
        tiles = tiles.crossJoin(F.broadcast(particles.select(*keys).distinct() if steps is None else steps))
    full = tiles.join(counts, [*keys, "tile_id"], "left").withColumn("n_part", F.coalesce("n_part", F.lit(0).cast("bigint")))
    load = formula if formula is not None else F.col("n_part") * den + F.col("n_cells") * num
    return full.withColumn("load_u", load.cast("bigint")).select(*keys, "tile_id", *dom.tcols, "n_part", "n_cells", "load_u")


def ideal_load(load: DataFrame, n_pe: int, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Total load and the mean of n_pe equal shares."""
    return load.groupBy(*by).agg(F.sum("load_u").alias("total_u")).withColumn("ideal", F.col("total_u") / n_pe)


def project(load: DataFrame, axis: str, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Load summed over all axes but one."""
    return load.groupBy(*by, f"t{axis}").agg(F.sum("load_u").alias("load_u"))


def density(particles: DataFrame, dom: Domain, level: str = "tile", by: tuple[str, ...] = ("step", "species")) -> DataFrame:
    """Particles for each tile or cell that has any."""
    cols = ["tile_id"] if level == "tile" else dom.ccols
    return bin_particles(particles, dom).groupBy(*by, *cols).agg(F.count("*").alias("n_part"))
