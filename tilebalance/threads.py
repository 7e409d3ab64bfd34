"""Work inside a group: heavy tiles are shared by all threads, light ones take one each.

Times are in load units multiplied by the number of threads (time_t), so that
they stay integers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

MODES = ("hybrid", "light_only", "heavy_only", "no_tiles", "task")


def classify(assigned: DataFrame, threads: Column | int, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Adds is_heavy: the tile's load reaches its group's mean load a thread, or the group has fewer tiles than threads."""
    own = Window.partitionBy(*by, "pe")
    return assigned.withColumn("is_heavy", (F.col("load_u") * threads >= F.sum("load_u").over(own)) | (F.count("*").over(own) < threads))


def makespan(loads: Column, threads: Column | int) -> Column:
    """Largest clock after first-come scheduling of an array of loads, in order, each to a thread with the least clock (which of equal ones makes no difference to the largest).  The clocks are kept sorted, so a load costs one native sort of `threads` numbers."""
    clocks = F.array_repeat(F.lit(0).cast("bigint"), threads)
    put = lambda acc, load: F.sort_array(F.concat(F.slice(acc, 2, threads), F.array(F.get(acc, F.lit(0)) + load)))
    return F.aggregate(loads, clocks, put, F.array_max)


def pe_time(assigned: DataFrame, threads: Column | int, mode: str = "hybrid", by: tuple[str, ...] = ("step",), reduce_cost: int = 0, index: str = "curve_idx") -> DataFrame:
    """by, pe, load_u, n_tiles, n_heavy, time_t (time multiplied by threads).

    reduce_cost is charged for every cell of each block that threads share with
    private copies: threads * cells, in load units.  threads may be one of the
    key columns, so that many thread counts are one plan.
    """
    if mode not in MODES or mode == "task":
        raise ValueError(f"mode must be one of {MODES[:-1]}; tasks have task_time()")
    marked = classify(assigned, threads, by)
    heavy = {"hybrid": F.col("is_heavy"), "light_only": F.lit(False), "heavy_only": F.lit(True), "no_tiles": F.lit(True)}[mode]
    rows = marked.withColumn("_h", heavy)
    lights = F.transform(F.array_sort(F.collect_list(F.when(~F.col("_h"), F.struct(F.col(index).alias("i"), F.col("load_u").alias("l"))))), lambda t: t["l"])
    shared = F.sum(F.when(F.col("_h"), F.col("load_u")).otherwise(0))
    extra = F.sum(F.when(F.col("_h"), F.col("n_cells")).otherwise(0)) * (reduce_cost * threads * threads)
    out = rows.groupBy(*by, "pe").agg(F.sum("load_u").alias("load_u"), F.count("*").alias("n_tiles"), F.sum(F.col("is_heavy").cast("bigint")).alias("n_heavy"), lights.alias("_lights"), (shared + extra).alias("_shared"))
    return out.withColumn("time_t", makespan(F.col("_lights"), threads) * threads + F.col("_shared")).drop("_lights", "_shared")


def task_threads(assigned: DataFrame, threads: int, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Heavy tiles' shares of the threads by particles, rounded half up, from one to all."""
    own = Window.partitionBy(*by, "pe")
    share = F.floor((F.col("n_part") * (2 * threads) + F.col("_n")) / (2 * F.col("_n")))
    out = classify(assigned, threads, by).withColumn("_n", F.sum("n_part").over(own))
    return out.withColumn("slots", F.when(F.col("is_heavy"), F.greatest(F.lit(1), F.least(F.lit(threads), F.when(F.col("_n") > 0, share).otherwise(1)))).otherwise(1).cast("int")).drop("_n")


def task_time(assigned: DataFrame, threads: int, by: tuple[str, ...] = ("step",), index: str = "curve_idx") -> DataFrame:
    """by, pe, makespan of tasks: light tiles first, then heavy ones; one that needs q threads begins at the q-th smallest clock.  Sequential by nature, so one pandas call a group, over its tiles."""
    import pandas as pd

    keys = [*by, "pe"]

    def run(key, rows):
        clocks = [0.0] * threads
        for _, slots, load in rows.sort_values(["is_heavy", index])[["is_heavy", "slots", "load_u"]].itertuples(index=False):
            clocks.sort()
            begin = clocks[slots - 1]
            clocks[:slots] = [begin + load / slots] * slots
        return pd.DataFrame([[*key, float(max(clocks))]], columns=[*keys, "makespan"])

    need = task_threads(assigned, threads, by).select(*keys, index, "is_heavy", "slots", "load_u")
    kinds = dict(need.dtypes)
    return need.groupBy(*keys).applyInPandas(run, ", ".join(f"{k} {kinds[k]}" for k in keys) + ", makespan double")


def taskfarm(assigned: DataFrame, n_pe: int, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Own tiles first, then tiles of the group with most left: by, makespan, stolen, n_tasks.  One pandas call a step over its tiles."""
    import heapq

    import pandas as pd

    def run(key, rows):
        queue = {p: [] for p in range(n_pe)}
        for p, load in rows.sort_values("tile_id")[["pe", "load_u"]].itertuples(index=False):
            queue[p].append(int(load))
        queue = {p: q[::-1] for p, q in queue.items()}
        left = {p: sum(q) for p, q in queue.items()}
        clocks = [(0, p) for p in range(n_pe)]
        heapq.heapify(clocks)
        stolen = done = 0
        todo = sum(map(len, queue.values()))
        while todo:
            t, p = heapq.heappop(clocks)
            victim = p if queue[p] else min((q for q in queue if queue[q]), key=lambda q: (-left[q], q))
            load = queue[victim].pop()
            left[victim] -= load
            stolen += victim != p
            done, todo = done + 1, todo - 1
            heapq.heappush(clocks, (t + load, p))
        return pd.DataFrame([[*key, max(t for t, _ in clocks), stolen, done]], columns=[*by, "makespan", "stolen", "n_tasks"])

    kinds = dict(assigned.dtypes)
    return assigned.select(*by, "tile_id", "pe", "load_u").groupBy(*by).applyInPandas(run, ", ".join(f"{k} {kinds[k]}" for k in by) + ", makespan bigint, stolen bigint, n_tasks bigint")


def alpha(load: DataFrame, n_pe: int, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Slow-down by the fullest tile: its load over the mean load of a group, one at least."""
    out = load.groupBy(*by).agg(F.max("load_u").alias("max_tile_u"), F.sum("load_u").alias("total_u"))
    return out.withColumn("alpha", F.greatest(F.lit(1.0), F.col("max_tile_u") * n_pe / F.col("total_u")))


def split_heavy(particles: DataFrame, heavy: DataFrame, threads: int, key: str = "pid") -> DataFrame:
    """Slot of each particle: rows of heavy tiles are dealt over all threads by their key, others keep slot 0.  heavy has tile_id; it is short (few tiles are heavy) and joined as Spark sees fit."""
    marked = particles.join(heavy.select("tile_id", F.lit(True).alias("_h")), "tile_id", "left")
    return marked.withColumn("slot", F.when(F.col("_h"), F.pmod(F.col(key), F.lit(threads))).otherwise(0).cast("int")).drop("_h")


def slot_plan(assigned: DataFrame, threads: int, by: tuple[str, ...] = ("step",), index: str = "curve_idx") -> DataFrame:
    """by, tile_id, pe, load_u, is_heavy, slot: the thread of each light tile by the schedule of makespan(); heavy tiles have none (null), as all threads share them."""
    rows = classify(assigned, threads, by)
    light = F.array_sort(F.collect_list(F.when(~F.col("is_heavy"), F.struct(F.col(index).alias("i"), F.col("load_u").alias("l"), F.col("tile_id").alias("t")))))
    start = F.struct(F.array_repeat(F.lit(0).cast("bigint"), threads).alias("clocks"), F.array().cast("array<struct<tile_id:bigint,slot:int>>").alias("out"))

    def put(acc: Column, tile: Column) -> Column:
        at = (F.array_position(acc["clocks"], F.array_min(acc["clocks"])) - 1).cast("int")
        clocks = F.transform(acc["clocks"], lambda c, i: F.when(i == at, c + tile["l"]).otherwise(c))
        return F.struct(clocks.alias("clocks"), F.concat(acc["out"], F.array(F.struct(tile["t"].cast("bigint").alias("tile_id"), at.alias("slot")))).alias("out"))

    slots = rows.groupBy(*by, "pe").agg(light.alias("_l")).select(*by, F.inline(F.aggregate("_l", start, put, lambda acc: acc["out"])))
    return rows.join(slots, [*by, "tile_id"], "left").select(*by, "tile_id", "pe", "load_u", "is_heavy", "slot")


def plan_time(plan: DataFrame, threads: int, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """by, pe, n_heavy, time_t of a slot plan: the fullest slot times threads, plus the heavy tiles' load."""
    own = plan.groupBy(*by, "pe", "slot").agg(F.sum("load_u").alias("s"), F.sum(F.col("is_heavy").cast("bigint")).alias("h"))
    shared, alone = F.max(F.when(F.col("slot").isNull(), F.col("s"))), F.max(F.when(F.col("slot").isNotNull(), F.col("s")))
    return own.groupBy(*by, "pe").agg(F.sum("h").alias("n_heavy"), (F.coalesce(alone, F.lit(0)) * threads + F.coalesce(shared, F.lit(0))).cast("bigint").alias("time_t"))


def place_hybrid(particles: DataFrame, plan: DataFrame, n_pe: int, threads: int, by: tuple[str, ...] = ("step",)) -> DataFrame:
    """Particles (with tile_id) in n_pe * threads partitions: those of light tiles in partition pe * threads + slot, those of heavy tiles dealt over all slots of their group in turn, so equal rows are dealt too."""
    turn = F.pmod(F.monotonically_increasing_id(), F.lit(threads)).cast("int")
    marked = particles.withColumn("_turn", turn).join(plan.select(*by, "tile_id", "pe", "slot"), [*by, "tile_id"])
    part = (F.col("pe") * threads + F.coalesce("slot", "_turn")).cast("int")
    return marked.withColumn("part", part).drop("_turn", "slot").repartitionById(n_pe * threads, F.col("part"))


def private_sums(placed: DataFrame, keys: list[str], amounts: dict[str, Column]) -> DataFrame:
    """Sums by keys over placed rows: each partition adds up its own copy, without a shuffle; the copies of shared cells are then added up."""
    first = placed.groupBy("part", *keys).agg(*[F.sum(c).alias(n) for n, c in amounts.items()])
    return first.groupBy(*keys).agg(*[F.sum(n).alias(n) for n in amounts])
