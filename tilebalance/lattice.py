"""Domains, tiles and the binning of particles.

A domain is a box of cells cut into equal tiles.  All of it is scalars; tables
of tiles are made by spark.range, so that empty tiles, whose cells still cost
work, are never forgotten.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from math import prod

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

AXES = ("x", "y", "z")
#: Fewest cells a tile may have on an axis for each particle shape order.
LEAST_SIDE = {0: 1, 1: 3, 2: 5}


@dataclass(frozen=True)
class Domain:
    cells: tuple[int, ...]
    tile: tuple[int, ...]
    periodic: bool = True
    order: int = 2

    @property
    def dims(self) -> int:
        return len(self.cells)

    @property
    def tiles(self) -> tuple[int, ...]:
        return tuple(c // t for c, t in zip(self.cells, self.tile))

    @property
    def n_tiles(self) -> int:
        return prod(self.tiles)

    @property
    def cells_per_tile(self) -> int:
        return prod(self.tile)

    @property
    def axes(self) -> tuple[str, ...]:
        return AXES[: self.dims]

    @property
    def tcols(self) -> list[str]:
        return [f"t{a}" for a in self.axes]

    @property
    def ccols(self) -> list[str]:
        return [f"c{a}" for a in self.axes]

    def validate(self) -> "Domain":
        if not 1 <= self.dims <= 3 or len(self.tile) != self.dims:
            raise ValueError("a domain has one to three axes, cells and tile sides for each")
        for c, t in zip(self.cells, self.tile):
            if t < 1 or c % t:
                raise ValueError(f"{c} cells are not a multiple of the tile side {t}")
            if t < LEAST_SIDE[self.order]:
                raise ValueError(f"tile side {t} is below {LEAST_SIDE[self.order]}, the least for shape order {self.order}")
        return self


def with_tile_side(dom: Domain, side: int) -> Domain:
    """The same box under cubic tiles of another side."""
    return replace(dom, tile=(side,) * dom.dims).validate()


def tile_id(dom: Domain) -> Column:
    """Row-major number of a tile, x fastest."""
    out, step = F.lit(0).cast("bigint"), 1
    for col, n in zip(dom.tcols, dom.tiles):
        out, step = out + F.col(col).cast("bigint") * step, step * n
    return out


def bin_particles(df: DataFrame, dom: Domain) -> DataFrame:
    """Adds tile coordinates and tile_id to rows with cell coordinates cx, cy, cz: a projection, no exchange."""
    out = df.withColumns({t: F.expr(f"cast({c} div {s} as int)") for t, c, s in zip(dom.tcols, dom.ccols, dom.tile)})
    return out.withColumn("tile_id", tile_id(dom))


def apply_boundary(df: DataFrame, dom: Domain, mode: str = "wrap") -> DataFrame:
    """Brings cell coordinates into the box: wrap around, clamp to the border, or drop what is outside."""
    pairs = list(zip(dom.ccols, dom.cells))
    if mode == "wrap":
        return df.withColumns({c: F.pmod(F.col(c), F.lit(n)) for c, n in pairs})
    if mode == "clamp":
        return df.withColumns({c: F.greatest(F.lit(0), F.least(F.col(c), F.lit(n - 1))) for c, n in pairs})
    if mode == "drop":
        for c, n in pairs:
            df = df.where(F.col(c).between(0, n - 1))
        return df
    raise ValueError(f"unknown boundary {mode}")


def lattice(spark: SparkSession, dom: Domain) -> DataFrame:
    """Every tile: tile_id, its coordinates, n_cells."""
    df, step, cols = spark.range(dom.n_tiles).withColumnRenamed("id", "tile_id"), 1, {}
    for t, n in zip(dom.tcols, dom.tiles):
        cols[t] = F.expr(f"cast((tile_id div {step}) % {n} as int)")
        step *= n
    return df.withColumns(cols).withColumn("n_cells", F.lit(dom.cells_per_tile).cast("bigint"))
