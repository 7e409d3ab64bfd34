"""The loop of rebalancing: which map holds at which step, and what moves between maps."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import metrics


def epochs(load: DataFrame, every: int | None) -> DataFrame:
    """Adds epoch, the step whose map holds: the last multiple of `every`, or step 0 (None)."""
    return load.withColumn("epoch", F.lit(0) if every is None else F.col("step") - F.col("step") % every)


def charge(load: DataFrame, maps: DataFrame, every: int | None) -> DataFrame:
    """Each step's load under the map made at its epoch: an equi-join on (epoch, tile)."""
    held = maps.select(F.col("step").alias("epoch"), "tile_id", "pe")
    return epochs(load, every).join(held, ["epoch", "tile_id"])


def run(load: DataFrame, make: Callable[[DataFrame], DataFrame], every: int | None) -> DataFrame:
    """Maps are made from scratch at the epochs' steps and charged with the loads of all steps."""
    first = F.col("step") == 0 if every is None else F.col("step") % every == 0
    return charge(load, make(load.where(first)), every)


def migration(maps: DataFrame, every: int) -> DataFrame:
    """What moves at each new epoch: epoch, src_pe, dst_pe, n_tiles, n_part, n_cells (the payload is that of the new epoch's first step)."""
    old = maps.select((F.col("step") + every).alias("step"), "tile_id", F.col("pe").alias("src_pe"))
    moved = maps.join(old, ["step", "tile_id"]).where("src_pe <> pe")
    return moved.groupBy(F.col("step").alias("epoch"), "src_pe", F.col("pe").alias("dst_pe")).agg(F.count("*").alias("n_tiles"), F.sum("n_part").alias("n_part"), F.sum("n_cells").alias("n_cells"))


def messages(plan: DataFrame, grouped: bool) -> DataFrame:
    """A buffer for each pair of groups, or one for each tile."""
    return plan.groupBy("epoch").agg((F.count("*") if grouped else F.sum("n_tiles")).alias("n_messages"))


def threshold(load: DataFrame, make: Callable[[DataFrame], DataFrame], n_pe: int, limit: float) -> list[tuple[int, float, bool]]:
    """(step, imbalance before any new map, whether one was made): a new map whenever the one held is worse than limit.  Sequential: one row a step reaches the driver."""
    steps = sorted(r.step for r in load.select("step").distinct().collect())
    held, out = make(load.where(F.col("step") == steps[0])).select("tile_id", "pe"), []
    for s in steps:
        own = load.where(F.col("step") == s)
        worst = metrics.imbalance(own.join(held, "tile_id"), n_pe).first().imbalance
        again = worst > limit
        if again:
            held = make(own).select("tile_id", "pe")
        out.append((s, float(worst), again))
    return out
