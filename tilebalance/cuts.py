"""Cutting a line of loads into contiguous groups of about equal load."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def cut_prefix(ordered: DataFrame, n_pe: Column | int, by: tuple[str, ...] = ("step",), index: str = "curve_idx", out: str = "pe") -> DataFrame:
    """Adds the group of each tile by the midpoint rule; no group exceeds the mean by more than the largest tile."""
    line = Window.partitionBy(*by).orderBy(index)
    whole = Window.partitionBy(*by)
    cum = F.sum("load_u").over(line.rowsBetween(Window.unboundedPreceding, 0))
    named = ordered.withColumns({"_cum": cum, "_total": F.sum("load_u").over(whole), "_at": F.row_number().over(line) - 1, "_n": F.count("*").over(whole)})
    n = n_pe if isinstance(n_pe, Column) else F.lit(n_pe)
    mid = F.expr("cast(2 * _cum - load_u as decimal(20,0))") * n.cast("decimal(10,0)")
    group = F.when(F.col("_total") > 0, F.floor(F.try_divide(mid, F.expr("cast(2 * _total as decimal(20,0))")))).otherwise(F.floor(F.col("_at") * n / F.col("_n")))
    return named.withColumn(out, F.least(group.cast("int"), (n - 1).cast("int"))).drop("_cum", "_total", "_at", "_n")


def prefix_sum_blocked(ordered: DataFrame, block: int, index: str = "curve_idx") -> DataFrame:
    """cum_u along the whole line without one task that sees all of it: sums of blocks, their prefix, and a prefix inside each block.  Only one row a block passes the single-partition window."""
    named = ordered.withColumn("_block", F.expr(f"cast({index} div {block} as bigint)"))
    sums = named.groupBy("_block").agg(F.sum("load_u").alias("_s"))
    before = sums.select("_block", F.coalesce(F.sum("_s").over(Window.orderBy("_block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    own = Window.partitionBy("_block").orderBy(index).rowsBetween(Window.unboundedPreceding, 0)
    return named.join(before, "_block").withColumn("cum_u", F.col("_before") + F.sum("load_u").over(own)).drop("_block", "_before")


def first_indices(assigned: DataFrame, n_pe: Column | int, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """One row for each key: cuts, the array of the first position of each group (a group without tiles begins where the next does), and m, the tiles."""
    counts = assigned.groupBy(*by, "pe").agg(F.count("*").alias("_n"))
    own = counts.groupBy(*by).agg(F.sum("_n").alias("m")).withColumn("pe", F.explode(F.sequence(F.lit(0), F.lit(n_pe) - 1)))
    before = Window.partitionBy(*by).orderBy("pe").rowsBetween(Window.unboundedPreceding, -1)
    line = own.join(counts, [*by, "pe"], "left").withColumn("_c", F.coalesce(F.sum("_n").over(before), F.lit(0).cast("bigint")))
    return line.groupBy(*by).agg(F.transform(F.array_sort(F.collect_list(F.struct("pe", "_c"))), lambda x: x["_c"]).alias("cuts"), F.first("m").alias("m"))


def nonempty_cuts(cuts: DataFrame, n_pe: Column | int) -> DataFrame:
    """Shifts cuts so that every group has a tile: cut k becomes k plus the running maximum of cut j - j, at most m - (n - k)."""
    fold = F.aggregate(
        F.transform("cuts", lambda c, k: c - k),
        F.struct(F.lit(-1).cast("bigint").alias("top"), F.array().cast("array<bigint>").alias("out")),
        lambda acc, x: F.struct(F.greatest(acc["top"], x).alias("top"), F.concat(acc["out"], F.array(F.greatest(acc["top"], x))).alias("out")),
        lambda acc: acc["out"],
    )
    return cuts.withColumn("cuts", F.transform(fold, lambda top, k: F.least(top + k, F.col("m") - n_pe + k)))


def assign_by_cuts(ordered: DataFrame, cuts: DataFrame, by: tuple[str, ...] = ("step",), index: str = "curve_idx") -> DataFrame:
    """Group of each row as the number of cuts at or before its index, found by halving: the map is n_pe longs a key, broadcast."""
    halves = F.transform(F.sequence(F.floor(F.log2(F.size("cuts"))).cast("int"), F.lit(0), F.lit(-1)), lambda k: F.call_function("shiftleft", F.lit(1), k))
    keyed = cuts.select(*by, "cuts", halves.alias("_halves"))
    joined = ordered.join(F.broadcast(keyed), list(by)) if by else ordered.crossJoin(F.broadcast(keyed))
    found = F.aggregate("_halves", F.lit(0), lambda n, s: F.when(F.get("cuts", n + s - 1) <= F.col(index), n + s).otherwise(n))
    return joined.withColumn("pe", found - 1).drop("cuts", "_halves")


def ensure_nonempty(ordered: DataFrame, assigned: DataFrame, n_pe: Column | int, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """ordered with repaired groups; its index must count 0, 1, ...  More groups than tiles is an error (raised when run)."""
    cuts = first_indices(assigned, n_pe, by)
    checked = cuts.withColumn("m", F.when(F.col("m") >= n_pe, F.col("m")).otherwise(F.raise_error(F.lit("more groups than tiles")).cast("bigint")))
    return assign_by_cuts(ordered.drop("pe"), nonempty_cuts(checked, n_pe), by)


def _lines(ordered: DataFrame, by: tuple[str, ...], index: str) -> DataFrame:
    return ordered.groupBy(*by).agg(F.array_sort(F.collect_list(F.struct(F.col(index).alias("i"), F.col("load_u").alias("l")))).alias("_line"), F.sum("load_u").alias("_total")).withColumn("_loads", F.transform("_line", lambda t: t["l"]))


def greedy_cuts(ordered: DataFrame, n_pe: int, target: str = "fixed", by: tuple[str, ...] = ("step",), index: str = "curve_idx") -> DataFrame:
    """by, cuts, m: fill a group while the next tile brings it nearer to its target, which is the mean ("fixed") or the mean of what remains ("adaptive").  A group keeps one tile at least and leaves one for each later group.  Lines are of bounded length (tiles, not particles)."""
    lines = _lines(ordered, by, index)
    n, total = F.lit(n_pe).cast("bigint"), F.col("_total")
    start = F.struct(F.lit(0).cast("bigint").alias("k"), F.lit(0).cast("bigint").alias("s"), F.lit(0).cast("bigint").alias("i"), F.lit(0).cast("bigint").alias("done"), F.array(F.lit(0).cast("bigint")).alias("cuts"))

    def step(acc: Column, load: Column) -> Column:
        share, goal = (n, total) if target == "fixed" else (n - acc["k"], total - acc["done"])
        nearer = F.abs((acc["s"] + load) * share - goal) < F.abs(acc["s"] * share - goal)
        left = F.size("_loads") - acc["i"]  # this tile included
        last = acc["k"] == n - 1
        stay = (acc["i"] == 0) | last | (nearer & (left > n - 1 - acc["k"]))
        return F.when(stay, F.struct(acc["k"].alias("k"), (acc["s"] + load).alias("s"), (acc["i"] + 1).alias("i"), acc["done"].alias("done"), acc["cuts"].alias("cuts"))).otherwise(
            F.struct((acc["k"] + 1).alias("k"), load.alias("s"), (acc["i"] + 1).alias("i"), (acc["done"] + acc["s"]).alias("done"), F.concat(acc["cuts"], F.array(acc["i"])).alias("cuts"))
        )

    return lines.select(*by, F.aggregate("_loads", start, step, lambda acc: acc["cuts"]).alias("cuts"), F.size("_loads").cast("bigint").alias("m"))


def cut_greedy(ordered: DataFrame, n_pe: int, target: str = "fixed", by: tuple[str, ...] = ("step",), index: str = "curve_idx") -> DataFrame:
    return assign_by_cuts(ordered, greedy_cuts(ordered, n_pe, target, by, index), by, index)


def minimax(ordered: DataFrame, n_pe: int, by: tuple[str, ...] = ("step",), index: str = "curve_idx") -> DataFrame:
    """by, bottleneck_u: the least possible load of the fullest of n_pe contiguous groups, by bisection with a filling probe."""
    lines = _lines(ordered, by, index)
    need = lambda limit: F.aggregate(
        "_loads", F.struct(F.lit(1).alias("k"), F.lit(0).cast("bigint").alias("s")),
        lambda acc, load: F.when(acc["s"] + load > limit, F.struct((acc["k"] + 1).alias("k"), load.alias("s"))).otherwise(F.struct(acc["k"].alias("k"), (acc["s"] + load).alias("s"))),
        lambda acc: acc["k"],
    )
    bounds = F.struct(F.greatest(F.array_max("_loads"), F.expr(f"(_total + {n_pe - 1}) div {n_pe}")).alias("lo"), F.col("_total").alias("hi"))

    def halve(acc: Column, _: Column) -> Column:
        mid = F.floor((acc["lo"] + acc["hi"]) / 2).cast("bigint")
        ok = need(mid) <= n_pe
        return F.struct(F.when(ok, acc["lo"]).otherwise(F.least(mid + 1, acc["hi"])).alias("lo"), F.when(ok, mid).otherwise(acc["hi"]).alias("hi"))

    return lines.select(*by, F.aggregate(F.sequence(F.lit(1), F.lit(63)), bounds, halve, lambda acc: acc["hi"]).alias("bottleneck_u"))
