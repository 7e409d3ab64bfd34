"""Measures of balance, speed and communication."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .lattice import Domain


def pe_loads(assigned: DataFrame, by: tuple[str, ...] = ("step",), what: str = "load_u") -> DataFrame:
    return assigned.groupBy(*by, "pe").agg(F.sum(what).alias("load_u"), F.count("*").alias("n_tiles"))


def imbalance(assigned: DataFrame, n_pe: int, by: tuple[str, ...] = ("step",), what: str = "load_u") -> DataFrame:
    """Largest load over the mean of all n_pe groups; groups without tiles count."""
    out = pe_loads(assigned, by, what).groupBy(*by).agg(F.max("load_u").alias("max_u"), F.sum("load_u").alias("total_u"))
    return out.withColumn("imbalance", F.round(F.col("max_u") * n_pe / F.col("total_u"), 6))


def imbalance_summary(per_step: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    return per_step.groupBy(*by).agg(F.max("imbalance").alias("peak"), F.round(F.avg("imbalance"), 6).alias("mean"))


def cumulative_balance(per_step: DataFrame, n_pe: int, by: tuple[str, ...] = ()) -> DataFrame:
    """Sum of the largest loads over the sum of the mean loads."""
    return per_step.groupBy(*by).agg(F.round(F.sum("max_u") * n_pe / F.sum("total_u"), 6).alias("cumulative"))


def core_load(times: DataFrame, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Largest time of any group, in load units times threads."""
    return times.groupBy(*by).agg(F.max("time_t").alias("core_t"), F.sum("load_u").alias("total_u"))


def concentration(load: DataFrame, percent: int = 70, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Fewest tiles that hold the percentage of the particles, and their share of all tiles."""
    fullest = Window.partitionBy(*by).orderBy(F.desc("n_part"), "tile_id")
    every = Window.partitionBy(*by)
    ranked = load.select(*by, F.row_number().over(fullest).alias("r"), F.sum("n_part").over(fullest.rowsBetween(Window.unboundedPreceding, 0)).alias("c"), F.sum("n_part").over(every).alias("n"), F.count("*").over(every).alias("m"))
    return ranked.where(F.col("c") * 100 >= F.col("n") * percent).groupBy(*by).agg(F.min("r").cast("bigint").alias("n_tiles"), F.first("m").alias("m")).select(*by, "n_tiles", F.round(F.col("n_tiles") / F.col("m"), 6).alias("share"))


def heavy_stats(classified: DataFrame, by: tuple[str, ...] = ("step",)) -> DataFrame:
    return classified.groupBy(*by).agg(F.sum(F.col("is_heavy").cast("bigint")).alias("n_heavy"), F.count("*").alias("n_tiles")).withColumn("share", F.round(F.col("n_heavy") / F.col("n_tiles"), 6))


def hot_spread(assigned: DataFrame, percent: int = 70, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Groups that own the tiles of concentration()."""
    fullest = Window.partitionBy(*by).orderBy(F.desc("n_part"), "tile_id")
    every = Window.partitionBy(*by)
    named = assigned.select(*by, "pe", (F.sum("n_part").over(fullest.rowsBetween(Window.unboundedPreceding, 0)) - F.col("n_part")).alias("c"), F.sum("n_part").over(every).alias("n"))
    return named.where(F.col("c") * 100 < F.col("n") * percent).groupBy(*by).agg(F.countDistinct("pe").alias("n_pe"), F.count("*").alias("n_tiles"))


def tiles_per_pe(assigned: DataFrame, n_pe: int, by: tuple[str, ...] = ("step",)) -> DataFrame:
    counts = pe_loads(assigned, by).groupBy(*by).agg(F.sum("n_tiles").alias("m"), F.min("n_tiles").alias("least"), F.count("*").alias("present"))
    return counts.select(*by, F.round(F.col("m") / n_pe, 6).alias("mean_tiles"), F.when(F.col("present") < n_pe, 0).otherwise(F.col("least")).cast("bigint").alias("least_tiles"))


def surface_volume(classified_edges: DataFrame, assigned: DataFrame, dom: Domain) -> DataFrame:
    """pe, external faces, their cells, and the cells of the group."""
    both = classified_edges.where("external").select(F.explode(F.array("a_pe", "b_pe")).alias("pe"), F.element_at(F.array(*[F.lit(dom.cells_per_tile // t) for t in dom.tile]), F.col("axis") + 1).alias("face"))
    area = both.groupBy("pe").agg(F.count("*").alias("n_faces"), F.sum("face").cast("bigint").alias("surface_cells"))
    return assigned.groupBy("pe").agg(F.sum("n_cells").alias("volume_cells")).join(area, "pe", "left").select("pe", F.coalesce("n_faces", F.lit(0)).alias("n_faces"), F.coalesce("surface_cells", F.lit(0)).alias("surface_cells"), "volume_cells")
