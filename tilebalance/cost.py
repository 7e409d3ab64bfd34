"""A rational cost model that stands in for the seconds of a machine.

A step lasts as long as its slowest group: the group's time (+ an unthreaded
share) + its border messages, border cells and crossing particles; the first
step of an epoch also waits for the group that sends most.  All parameters are
integers, in load units; times are in hundredths of them times the threads.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .lattice import Domain


@dataclass(frozen=True)
class Cost:
    latency: int = 50
    per_cell: int = 1
    per_part: int = 2
    migrate_part: int = 2
    migrate_cell: int = 1
    reduce: int = 0
    serial_percent: int = 0


def border_cost(classified: DataFrame, dom: Domain, cost: Cost = Cost(), by: tuple[str, ...] = ("step",)) -> DataFrame:
    """by, pe, comm_u: what a group sends in a step, a message for each axis round and neighbour and the cells of its external faces."""
    face = F.element_at(F.array(*[F.lit(dom.cells_per_tile // s) for s in dom.tile]), F.col("axis") + 1)
    ext = classified.where("external").withColumn("_cells", face)
    both = ext.select(*by, "axis", F.col("a_pe").alias("pe"), F.col("b_pe").alias("other"), "_cells").unionByName(ext.select(*by, "axis", F.col("b_pe").alias("pe"), F.col("a_pe").alias("other"), "_cells"))
    rounds = both.groupBy(*by, "pe", "axis", "other").agg(F.sum("_cells").alias("_cells"))
    return rounds.groupBy(*by, "pe").agg((F.count("*") * cost.latency + F.sum("_cells") * cost.per_cell).alias("comm_u"))


def crossing_cost(crossed: DataFrame, cost: Cost = Cost(), by: tuple[str, ...] = ("step",)) -> DataFrame:
    """by, pe, comm_u: the particles that a group sends to others, from exchange.crossings."""
    return crossed.where("remote").groupBy(*by, F.col("src_pe").alias("pe")).agg((F.sum("n_part") * cost.per_part).alias("comm_u"))


def migration_cost(plan: DataFrame, cost: Cost = Cost()) -> DataFrame:
    """step, migrate_u: what the group that sends most sends at each new epoch, from rebalance.migration."""
    sent = plan.groupBy("epoch", "src_pe").agg((F.count("*") * cost.latency + F.sum("n_part") * cost.migrate_part + F.sum("n_cells") * cost.migrate_cell).alias("_u"))
    return sent.groupBy(F.col("epoch").alias("step")).agg(F.max("_u").alias("migrate_u"))


def step_time(times: DataFrame, threads: Column | int, comm: DataFrame | None = None, cost: Cost = Cost(), by: tuple[str, ...] = ("step",)) -> DataFrame:
    """by, time_t: the slowest group's time with its border work (rows of comm with by, pe, comm_u are added up); a share of each group's load is not threaded."""
    work = F.col("time_t") * (100 - cost.serial_percent) + F.col("load_u") * (cost.serial_percent * threads)
    own = times.select(*by, "pe", work.alias("_t"))
    if comm is not None:
        sums = comm.groupBy(*by, "pe").agg(F.sum("comm_u").alias("_c"))
        own = own.join(sums, [*by, "pe"], "left").withColumn("_t", F.col("_t") + F.coalesce("_c", F.lit(0).cast("bigint")) * (100 * threads))
    return own.groupBy(*by).agg(F.max("_t").alias("time_t"))


def run_time(steps: DataFrame, threads: int, moved: DataFrame | None = None, repeat: int = 1) -> DataFrame:
    """time_t of a run: each of the given steps counts `repeat` times, each migration once."""
    out = steps.select((F.col("time_t") * repeat).alias("_t"))
    if moved is not None:
        out = out.unionByName(moved.select((F.col("migrate_u") * (100 * threads)).alias("_t")))
    return out.agg(F.sum("_t").alias("time_t"))
