"""Heavy keys are split over slots, light keys keep one: for aggregates and joins on skewed keys."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def heavy_keys(df: DataFrame, keys: Sequence[str], slots: int, least: int = 2) -> DataFrame:
    """Keys that hold at least 1/slots of the rows (so slots of them at most) with `least` rows or more; counted map-side."""
    counts = df.groupBy(*keys).agg(F.count("*").alias("_n"))
    total = df.agg(F.count("*").alias("_all"))
    return counts.crossJoin(F.broadcast(total)).where((F.col("_n") * slots >= F.col("_all")) & (F.col("_n") >= least)).select(*keys)


def balanced_agg(df: DataFrame, keys: Sequence[str], partial: dict[str, Column], final: dict[str, Column], slots: int = 8) -> DataFrame:
    """Two explicit stages: by (key, slot) with `partial`, then by key with `final`, which reads the partial columns.

    Useful where the first aggregate cannot combine map-side, such as collected
    or sorted groups; a slot is a hash of the row, so any key spreads evenly.
    """
    salted = df.withColumn("_slot", F.pmod(F.xxhash64(*df.columns), F.lit(slots)))
    first = salted.groupBy(*keys, "_slot").agg(*[c.alias(n) for n, c in partial.items()])
    return first.groupBy(*keys).agg(*[c.alias(n) for n, c in final.items()])


def balanced_join(left: DataFrame, right: DataFrame, keys: Sequence[str], slots: int = 8) -> DataFrame:
    """Inner join in which rows of left's heavy keys are dealt over slots and right's rows of those keys copied to each slot.  The heavy list has at most `slots` rows and is broadcast."""
    hot = F.broadcast(heavy_keys(left, keys, slots).withColumn("_hot", F.lit(True)))
    a = left.join(hot, list(keys), "left").withColumn("_slot", F.when(F.col("_hot"), F.pmod(F.xxhash64(*left.columns), F.lit(slots))).otherwise(0)).drop("_hot")
    b = right.join(hot, list(keys), "left").withColumn("_slot", F.explode(F.when(F.col("_hot"), F.sequence(F.lit(0), F.lit(slots - 1))).otherwise(F.array(F.lit(0))))).drop("_hot")
    return a.join(b.withColumn("_slot", F.col("_slot").cast("bigint")), [*keys, "_slot"]).drop("_slot")
