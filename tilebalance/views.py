"""Particle views of the given tables: each table row is a particle with integer cell coordinates.

A view's formulas are text in the common part of both SQL dialects; DIV stands
for truncating division (all numerators are positive).  Axis extents are row
counts of part, orders and supplier, whose keys run from 0.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .lattice import Domain

EXTENTS = {"np": "part", "no": "orders", "ns": "supplier"}


@dataclass(frozen=True)
class Source:
    """Rows of one table: named inner values, a filter, and the coordinates made from them and the step's parameter p."""

    table: str
    inner: dict[str, str]
    where: str
    cells: dict[str, str]
    species: str = "'all'"


@dataclass(frozen=True)
class View:
    dom: Domain
    n_pe: int
    grid: tuple[int, ...]
    weight: tuple[int, int]
    sources: tuple[Source, ...]
    steps: tuple[tuple[int, int], ...] = ((0, 0),)
    paper: dict = field(default_factory=dict, hash=False, compare=False)

    def sql(self) -> str:
        """The view as one DuckDB query: step, species, cx, cy[, cz]."""
        values = ", ".join(f"({s}, {p})" for s, p in self.steps)
        parts = []
        for s in self.sources:
            inner = ", ".join(f"{_fill(e, True)} AS {n}" for n, e in s.inner.items())
            cells = ", ".join(f"CAST({_fill(e, True)} AS BIGINT) AS {n}" for n, e in s.cells.items())
            parts.append(f"SELECT st.step, {s.species} AS species, {cells} FROM (SELECT * FROM (SELECT {inner} FROM {s.table}) WHERE {_fill(s.where, True)}) CROSS JOIN (VALUES {values}) st(step, p)")
        return " UNION ALL ".join(parts)

    def times(self, spark: SparkSession) -> DataFrame:
        """One row for each step."""
        return spark.createDataFrame([(s,) for s, _ in self.steps], "step int")

    def particles(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """The same rows as a DataFrame; scans read only the named columns."""
        sizes = {k: extent(spark, sf_dir, t) for k, t in EXTENTS.items()}
        steps = F.broadcast(spark.createDataFrame(list(self.steps), "step int, p bigint"))
        out = None
        for s in self.sources:
            rows = spark.read.parquet(f"{sf_dir}/{s.table}.parquet").selectExpr(*[f"{_fill(e, False, sizes)} AS {n}" for n, e in s.inner.items()]).where(_fill(s.where, False, sizes))
            own = rows.crossJoin(steps).selectExpr("step", f"{s.species} AS species", *[f"CAST({_fill(e, False, sizes)} AS BIGINT) AS {n}" for n, e in s.cells.items()])
            out = own if out is None else out.unionByName(own)
        return out


_COUNTS: dict[tuple[str, str], int] = {}


def extent(spark: SparkSession, sf_dir: str, table: str) -> int:
    """Rows of a table, from its Parquet footers."""
    if (sf_dir, table) not in _COUNTS:
        _COUNTS[sf_dir, table] = spark.read.parquet(f"{sf_dir}/{table}.parquet").count()
    return _COUNTS[sf_dir, table]


def _fill(text: str, duck: bool, sizes: dict[str, int] | None = None) -> str:
    for k, t in EXTENTS.items():
        text = text.replace("{" + k + "}", f"(SELECT count(*) FROM {t})" if duck else str(sizes[k]))
    text = text.replace("MICROS(ts)", "epoch_us(ts)" if duck else "CAST(CAST(CAST(ts - TIMESTAMP_NTZ'1970-01-01 00:00:00' AS INTERVAL SECOND) AS DECIMAL(20, 6)) * 1000000 AS BIGINT)")
    return text.replace(" DIV ", " // " if duck else " div ")


_X, _Y, _Q = "l_partkey * 2000 DIV {np}", "l_orderkey * 2000 DIV {no}", "(l_suppkey * 50 + CAST(l_quantity AS BIGINT) - 1) * 2000 DIV (50 * {ns})"
_KEYS = {"pk": "l_partkey", "ok": "l_orderkey", "sk": "l_suppkey"}
WAKE_STEPS = tuple((s, 210 - s * 190 // 160 if s < 160 else 20 + (s - 160) * 190 // 160) for s in range(0, 320, 20))


def _warm(n: int, tile: int, n_pe: int, grid: tuple[int, int]) -> View:
    return View(Domain((n, n), (tile, tile)), n_pe, grid, (1, 1), (Source("lineitem", _KEYS, "pk >= 0", {"cx": f"pk * {n} DIV {{np}}", "cy": f"ok * {n} DIV {{no}}"}),))


def _disc(tile: int = 10) -> View:
    ball = Source("lineitem", {"u": _X, "v": _Y}, "(u - 1000) * (u - 1000) + (v - 1000) * (v - 1000) <= 1000000", {"cx": "(80000 - 1000 * p + u * p) DIV 1000", "cy": "(80000 - 1000 * p + v * p) DIV 1000"})
    return View(Domain((160, 160), (tile, tile)), 16, (4, 4), (2, 1), (ball,), ((14, 14), (25, 25), (50, 50)))


def _ball(tile: int, n_pe: int, grid: tuple[int, int, int]) -> View:
    inside = "(u - 1000) * (u - 1000) + (v - 1000) * (v - 1000) + (q - 1000) * (q - 1000) <= 1000000"
    ball = Source("lineitem", {"u": _X, "v": _Y, "q": _Q, "st": "l_linestatus"}, inside, {c: f"(80000 - 1000 * p + {k} * p) DIV 1000" for c, k in (("cx", "u"), ("cy", "v"), ("cz", "q"))}, "st")
    weight = (4, 1000) if tile == 10 else (4, 1000)
    return View(Domain((160,) * 3, (tile,) * 3), n_pe, grid, weight, (ball,), ((14, 14), (25, 25), (50, 50)))


def _wake(radial: int, tile: tuple[int, int], weight: tuple[int, int], beam: str, n_pe: int = 32, grid: tuple[int, int] = (8, 4), steps=WAKE_STEPS) -> View:
    back = Source("lineitem", {"pk": "l_partkey", "ok": "l_orderkey", "ln": "l_linenumber"}, "ln <= 2", {"cx": "pk * 256 DIV {np}", "cy": f"ok * {radial} DIV {{no}}"}, "'background'")
    ev = Source("events", {"t": "MICROS(ts) - 1704067200000000", "r": "CAST(round(100 * value) AS BIGINT)"}, "r >= 0", {"cx": "t * 256 DIV 2592000000000", "cy": beam}, "'beam'")
    return View(Domain((256, radial), tile), n_pe, grid, weight, (back, ev), steps)


VIEWS: dict[str, View] = {
    "w1": _warm(128, 8, 16, (4, 4)),
    "w2": View(Domain((32,) * 3, (8,) * 3), 8, (2, 2, 2), (1, 1), (Source("lineitem", {**_KEYS, "qt": "CAST(l_quantity AS BIGINT)"}, "pk >= 0", {"cx": "pk * 32 DIV {np}", "cy": "ok * 32 DIV {no}", "cz": "(sk * 50 + qt - 1) * 32 DIV (50 * {ns})"}),)),
    "w5": View(Domain((128, 128), (8, 8)), 4, (2, 2), (1, 1), (Source("lineitem", _KEYS, "pk >= 0", {"cx": "pk * 128 DIV {np}", "cy": "(pk * 128 DIV {np} + sk * 16 DIV {ns} + 120) % 128"}),)),
    "w6": _ball(10, 64, (4, 4, 4)),
    "w6b": _ball(5, 256, (4, 8, 8)),
    "w7": _disc(),
    "w9": _wake(128, (8, 8), (1, 2), "least(127, r * p DIV (100 * 210 * 2))"),
    "w10": _wake(192, (8, 12), (1, 1), "least(191, r * p * 3 DIV (100 * 210 * 4))", steps=((0, 210), (160, 20), (300, 186))),
}
