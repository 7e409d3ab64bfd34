"""Orders of tiles: row-major, snake and Hilbert curves, as column expressions of tile coordinates.

Curve indices are computed on the rows of the load array, one row a tile; rows
of particles never need them once cuts are known.
"""

from __future__ import annotations

from functools import lru_cache
from itertools import permutations, product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .lattice import Domain, lattice


class CurveShapeError(ValueError):
    """The lattice has no Hilbert curve of this kind: its shortest side must be a power of two that divides the others."""


def row_major(dom: Domain) -> Column:
    out, step = F.lit(0).cast("bigint"), 1
    for t, n in zip(dom.tcols, dom.tiles):
        out, step = out + F.col(t).cast("bigint") * step, step * n
    return out


def snake_index(dom: Domain) -> Column:
    """Every other row is walked backwards; in three dimensions rows are first put in snake order over planes."""
    n = dom.tiles
    if dom.dims == 1:
        return F.col("tx").cast("bigint")
    back = lambda c, odd, size: F.when(F.pmod(odd, F.lit(2)) == 0, c).otherwise(size - 1 - c)
    row = F.col("ty").cast("bigint")
    if dom.dims == 3:
        row = back(row, F.col("tz"), n[1]) + F.col("tz").cast("bigint") * n[1]
    return back(F.col("tx").cast("bigint"), row, n[0]) + row * n[0]


def _side(dom: Domain) -> int:
    s = min(dom.tiles)
    if s & (s - 1) or any(n % s for n in dom.tiles):
        raise CurveShapeError(f"{dom.tiles} tiles")
    return s


def _hilbert_square(x: Column, y: Column, side: int) -> Column:
    """Index on a square: from the highest bit down, the quadrant's rank is added and the rest turned into the quadrant's frame."""
    state = F.struct(x.cast("bigint").alias("x"), y.cast("bigint").alias("y"), F.lit(0).cast("bigint").alias("d"))
    if side == 1:
        return F.lit(0).cast("bigint")

    def step(acc: Column, s: Column) -> Column:
        right, up = (acc["x"] >= s).cast("bigint"), (acc["y"] >= s).cast("bigint")
        ix, iy = acc["x"] - right * s, acc["y"] - up * s
        rank = F.when(right == 0, up).otherwise(3 - up)
        turned = F.when(up == 1, ix).when(right == 1, s - 1 - iy).otherwise(iy)
        other = F.when(up == 1, iy).when(right == 1, s - 1 - ix).otherwise(ix)
        return F.struct(turned.alias("x"), other.alias("y"), (acc["d"] + rank * s * s).alias("d"))

    sizes = F.array(*[F.lit(side >> k).cast("bigint") for k in range(1, side.bit_length())])
    return F.aggregate(sizes, state, step, lambda acc: acc["d"])


#: Fixed values of the three-dimensional curve.  Octants (x, y, z) in the order of the visit:
OCTANTS = ((0, 0, 0), (0, 1, 0), (0, 1, 1), (0, 0, 1), (1, 0, 1), (1, 1, 1), (1, 1, 0), (1, 0, 0))
#: and for each the copy that stands in it, as (axes taken, axes mirrored).
COPIES = (
    ((1, 0, 2), (0, 0, 0)), ((1, 2, 0), (0, 0, 0)), ((0, 1, 2), (0, 0, 0)), ((1, 0, 2), (1, 1, 0)),
    ((1, 0, 2), (0, 0, 0)), ((0, 1, 2), (0, 0, 0)), ((1, 2, 0), (1, 0, 1)), ((1, 0, 2), (1, 1, 0)),
)
Turn = tuple[tuple[int, ...], tuple[int, ...]]


def turned(t: Turn, v: tuple[int, ...]) -> tuple[int, ...]:
    return tuple(v[a] ^ f for a, f in zip(*t))


def after(outer: Turn, inner: Turn) -> Turn:
    """The turn that does inner first, then outer."""
    return tuple(inner[0][a] for a in outer[0]), tuple(inner[1][a] ^ f for a, f in zip(*outer))


@lru_cache
def turn_table() -> tuple[list[Turn], list[int]]:
    """All signed axis permutations, and for each turn and octant (x + 2y + 4z) eight times the next turn's number plus the octant's rank."""
    turns = [(p, f) for p in permutations(range(3)) for f in product((0, 1), repeat=3)]
    number = {t: k for k, t in enumerate(turns)}
    table = [0] * (8 * len(turns))
    for k, t in enumerate(turns):
        for rank, (octant, copy) in enumerate(zip(OCTANTS, COPIES)):
            x, y, z = turned(t, octant)
            table[8 * k + x + 2 * y + 4 * z] = 8 * number[after(t, copy)] + rank
    return turns, table


def _corner_walk(shape: tuple[int, ...]) -> list[int]:
    """Turn of each block of a stretched box along the snake of blocks, so that each begins beside where the last ended."""
    turns, _ = turn_table()
    order = sorted(product(*map(range, shape)), key=lambda b: _snake_rank(b, shape))
    ends = [(turned(t, (0, 0, 0)), turned(t, (1, 0, 0))) for t in turns]
    chosen: list[int] = []

    def entry(k: int) -> tuple[int, ...] | None:
        if not k:
            return (0, 0, 0)
        step = [b - a for a, b in zip(order[k - 1], order[k])]
        axis = next(i for i, d in enumerate(step) if d)
        end = ends[chosen[-1]][1]
        return tuple(1 - c if i == axis else c for i, c in enumerate(end))

    def fits(k: int, t: int) -> bool:
        begin, end = ends[t]
        if begin != entry(k):
            return False
        if k + 1 == len(order):
            return True
        step = [b - a for a, b in zip(order[k], order[k + 1])]
        axis = next(i for i, d in enumerate(step) if d)
        return end[axis] == (step[axis] > 0)

    tried = [iter(range(len(turns)))]
    while len(chosen) < len(order):
        k = len(chosen)
        found = next((t for t in tried[-1] if fits(k, t)), None)
        if found is None:
            tried.pop()
            if not chosen:
                raise CurveShapeError(f"no chain of curves through {shape} blocks")
            chosen.pop()
        else:
            chosen.append(found)
            tried.append(iter(range(len(turns))))
    return chosen


def _snake_rank(b: tuple[int, ...], shape: tuple[int, ...]) -> int:
    row = (b[1] if b[2] % 2 == 0 else shape[1] - 1 - b[1]) + b[2] * shape[1]
    return (b[0] if row % 2 == 0 else shape[0] - 1 - b[0]) + row * shape[0]


def hilbert_index(dom: Domain) -> Column:
    """Hilbert order of square or cubic lattices and of boxes whose sides are multiples of the shortest, a power of two."""
    if dom.dims == 1:
        return F.col("tx").cast("bigint")
    side, n = _side(dom), dom.tiles
    if dom.dims == 2:
        long, short = ("tx", "ty") if n[0] >= n[1] else ("ty", "tx")
        block = F.expr(f"cast({long} div {side} as bigint)")
        return block * side * side + _hilbert_square(F.col(long) - block * side, F.col(short), side)
    shape = tuple(k // side for k in n)
    blocks = _corner_walk(shape)
    _, table = turn_table()
    at = [F.expr(f"cast({t} div {side} as int)") for t in dom.tcols]
    row = F.when(F.pmod(at[2], F.lit(2)) == 0, at[1]).otherwise(shape[1] - 1 - at[1]) + at[2] * shape[1]
    rank = (F.when(F.pmod(row, F.lit(2)) == 0, at[0]).otherwise(shape[0] - 1 - at[0]) + row * shape[0]).cast("int")
    first = F.element_at(F.array(*map(F.lit, blocks)), rank + 1)
    state = F.struct(first.cast("int").alias("turn"), F.lit(0).cast("bigint").alias("d"))
    if side == 1:
        return rank.cast("bigint")
    inner = [F.col(t) % side for t in dom.tcols]

    def step(acc: Column, s: Column) -> Column:
        bit = [F.floor(i / s).cast("int") % 2 for i in inner]
        cell = F.element_at(F.array(*map(F.lit, table)), acc["turn"] * 8 + bit[0] + 2 * bit[1] + 4 * bit[2] + 1)
        return F.struct(F.shiftright(cell, 3).alias("turn"), (acc["d"] * 8 + cell % 8).alias("d"))

    sizes = F.array(*[F.lit(side >> k) for k in range(1, side.bit_length())])
    return rank.cast("bigint") * side**3 + F.aggregate(sizes, state, step, lambda acc: acc["d"])


def by_load(load: DataFrame, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """The rejected order: heaviest tile first, whatever its place."""
    return load.withColumn("curve_idx", (F.row_number().over(Window.partitionBy(*by).orderBy(F.desc("load_u"), "tile_id")) - 1).cast("bigint"))


INDEX = {"row_major": row_major, "snake": snake_index, "hilbert": hilbert_index}


#: Tiles up to which particles find their index in a broadcast table of the lattice (16 bytes a tile).
TABLE_TILES = 100_000


def index_particles(binned: DataFrame, dom: Domain, curve: str = "hilbert") -> DataFrame:
    """Adds curve_idx to rows with tile_id: computed once a tile and looked up; for more than TABLE_TILES tiles, computed for each row."""
    if dom.n_tiles > TABLE_TILES:
        return binned.withColumn("curve_idx", INDEX[curve](dom))
    table = lattice(binned.sparkSession, dom).select("tile_id", INDEX[curve](dom).alias("curve_idx"))
    return binned.join(F.broadcast(table), "tile_id", "left")


def gaps(ordered: DataFrame, dom: Domain) -> DataFrame:
    """Neighbours along curve_idx that do not share a face (for a contiguous curve: none)."""
    w = Window.orderBy("curve_idx")
    apart = sum((F.abs(F.col(t) - F.lag(t).over(w)) for t in dom.tcols), F.lit(0))
    return ordered.withColumn("apart", apart).where("apart <> 1").select("curve_idx", "apart")
