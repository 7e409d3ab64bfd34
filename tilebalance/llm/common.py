"""Helpers shared by the training-data operators: tables, durable cuts of lineage, connected components."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that a Python worker handles at a time.
SLICE_BYTES = 500_000
#: Rows of a bitmap, 4,096 numbers each in half a kilobyte, up to which it is broadcast.
BITMAP_ROWS = 1 << 17
#: Rows that materialise() has sent to Python at once: Spark's own 10,000 texts are many times a slice, in the executor and in the worker.
ARROW_ROWS = 1000
_KEPT: dict[str, dict] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share.  Only where none is set (tests) a folder of this machine is used."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        found = "file://" + tempfile.mkdtemp(prefix="shared-")
        spark.sparkContext.setCheckpointDir(found)
    return found


def fresh_path(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{what}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, what: str) -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: lineage ends here and survives lost executors."""
    path, conf, key = fresh_path(df.sparkSession, what), df.sparkSession.conf, "spark.sql.execution.arrow.maxRecordsPerBatch"
    given = conf.get(key, None)
    conf.set(key, str(ARROW_ROWS))
    try:
        df.write.parquet(path)
    finally:
        conf.unset(key) if given is None else conf.set(key, given)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def slices(texts: pa.Array, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of rows whose texts hold at most limit bytes together (one row at least)."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    a = 0
    while a < len(ends):
        b = max(a + 1, int(np.searchsorted(ends, limit + (ends[a - 1] if a else 0), side="right")))
        yield a, b
        a = b


def kept(operator: str) -> dict:
    """The models that this Python worker keeps for an operator from task to task."""
    return _KEPT.setdefault(operator, {})


def make_room(operator: str = "") -> None:
    """Forget, in this Python worker, the models of all operators but one: a worker serves one after another and would hold every one's."""
    held = [models for name, models in _KEPT.items() if models and name != operator]
    for models in held:
        models.clear()
    if held:
        gc.collect()


def give_back() -> None:
    """Return freed memory, which the allocators keep, to the system."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def tidy(run: Callable, operator: str = "") -> Callable:
    """run, a function of batches, with only its operator's models in memory; what it freed is given back at its end."""

    def task(batches):
        make_room(operator)
        give_back()
        yield from run(batches)
        give_back()

    return task


def forget(df: DataFrame) -> None:
    """Delete the files of a table made by materialise() that no plan needs any more."""
    session = df.sparkSession
    jvm, conf = session._jvm, session._jsc.hadoopConfiguration()
    for folder in {name.rsplit("/", 1)[0] for name in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(conf).delete(path, True)


def release(spark: SparkSession) -> None:
    """Have shuffles that no plan needs any more deleted now: Spark does so when the driver collects its garbage, which a small driver seldom does."""
    gc.collect()
    spark._jvm.System.gc()


def shrink(spark: SparkSession) -> None:
    """Have executors collect their garbage now: a heap stays as large as the stage before made it, beside the workers of the next.  A task a slot, so on a busy or large cluster some executors may be left out; no result depends on it."""
    slots = max(1, spark.sparkContext.defaultParallelism)
    spark.range(0, slots, 1, slots).select(F.java_method(F.lit("java.lang.System"), F.lit("gc"))).write.format("noop").mode("overwrite").save()


def bitmap(numbers: DataFrame, number: Column) -> DataFrame:
    """(_chunk, _bits): the numbers, 0 or more, as bits, 4,096 to a row; chunks without any are missing."""
    words = numbers.select(F.shiftright(number, 6).alias("w"), F.call_function("shiftleft", F.lit(1).cast("bigint"), number.bitwiseAND(63).cast("int")).alias("x")).groupBy("w").agg(F.bit_or("x").alias("x"))
    held = words.groupBy(F.shiftright("w", 6).alias("_chunk")).agg(F.map_from_entries(F.collect_list(F.struct(F.col("w").bitwiseAND(63).cast("int"), "x"))).alias("m"))
    bits = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0).cast("bigint")))
    return materialise(held.select("_chunk", bits.alias("_bits")), "bitmap")


def marked(df: DataFrame, number: Column, bits: DataFrame, how: str) -> DataFrame:
    """Rows of df whose number is in a bitmap (how: left_semi) or is not (left_anti)."""
    word = F.get("_bits", F.shiftright(number, 6).bitwiseAND(63).cast("int"))
    return df.join(F.broadcast(bits), (F.shiftright(number, 12) == F.col("_chunk")) & (F.getbit(word, number.bitwiseAND(63).cast("int")) == 1), how)


def by_row(df: DataFrame, ids: DataFrame, how: str) -> DataFrame:
    """Rows of df whose _row is among those of ids (left_semi) or is not (left_anti).  Rows numbered by monotonically_increasing_id() lie close, so a bitmap serves and df is not shuffled; one too large for broadcast gives way to an ordinary join."""
    bits = bitmap(ids, F.col("_row"))
    return marked(df, F.col("_row"), bits, how) if bits.count() <= BITMAP_ROWS else df.join(ids.select("_row"), "_row", how)


def components(edges: DataFrame, max_rounds: int = 200) -> DataFrame:
    """Connected components of undirected links (a, b), BIGINT.

    Result: (id, root) with one row per linked node, root the smallest node
    reachable.  Each round takes the least label among neighbours and then the
    label of that label (pointer jumping), so the number of rounds grows with
    the logarithm of the diameter.  Nothing but a change count reaches the
    driver.  Self links and nulls are ignored; an empty input gives no rows.
    """
    links = edges.select(F.col("a").cast("bigint"), F.col("b").cast("bigint")).where("a <> b")
    both = materialise(links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "links")
    labels = materialise(both.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("m")).select("id", F.least("id", "m").alias("root"), F.lit(True).alias("moved")), "labels")
    for _ in range(max_rounds):
        seen = both.join(labels.select(F.col("id").alias("b"), "root"), "b").groupBy(F.col("a").alias("id")).agg(F.min("root").alias("near"))
        hooked = labels.join(seen, "id").select("id", F.col("root").alias("old"), F.least("root", "near").alias("root"))
        jump = labels.select(F.col("id").alias("root"), F.col("root").alias("far"))
        following = materialise(
            hooked.join(jump, "root").select("id", F.least("root", "far").alias("root"), (F.least("root", "far") < F.col("old")).alias("moved")), "labels"
        )
        forget(labels)
        labels = following
        if labels.where("moved").isEmpty():
            forget(both)
            return labels.select("id", "root")
    raise RuntimeError(f"labels still move after {max_rounds} rounds")
