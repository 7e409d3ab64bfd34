"""The events table as a stream of particles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.files import scratch

_ROCKS = "spark.sql.streaming.stateStore.rocksdb"
#: A complete result's state is never dropped, so it is kept on disk, with one bound on memory for all partitions of a process.
ON_DISK = {"spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider", f"{_ROCKS}.boundedMemoryUsage": "true", f"{_ROCKS}.maxMemoryUsageMB": "200"}


def source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A file stream of events in the table's own schema."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    folder, name = path.rsplit("/", 1)
    return spark.readStream.schema(schema).option("pathGlobFilter", name).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def drain(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there and give its rows from Parquet files: appended ones, or the last batch's complete ones.  No rows come to the driver."""
    spark = df.sparkSession
    own = scratch(spark, "stream")
    if mode == "append":
        q = df.writeStream.format("parquet").option("path", f"{own}/rows").option("checkpointLocation", f"{own}/state").outputMode(mode).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{own}/rows")
    done = []

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{own}/rows/{number}")
        done.append(number)

    given = {k: spark.conf.get(k, None) for k in ON_DISK}
    for k, v in ON_DISK.items():
        spark.conf.set(k, v)
    try:
        q = df.writeStream.foreachBatch(write).option("checkpointLocation", f"{own}/state").outputMode(mode).trigger(availableNow=True).start()
    finally:
        for k, v in given.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{own}/rows/{done[-1]}") if done else spark.createDataFrame([], df.schema)


def each_batch(df: DataFrame, act: Callable[[DataFrame, int], None]) -> None:
    own = scratch(df.sparkSession, "stream")
    df.writeStream.foreachBatch(act).option("checkpointLocation", f"{own}/state").trigger(availableNow=True).start().awaitTermination()


def replay(parts: list[DataFrame], act: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Feed parts one after another to a stream that ends after each and starts again from its checkpoint; the rows appended by all runs."""
    spark = parts[0].sparkSession
    own, schema = scratch(spark, "stream"), parts[0].schema
    for part in parts:
        part.write.mode("append").parquet(f"{own}/in")
        out = act(spark.readStream.schema(schema).parquet(f"{own}/in"))
        out.writeStream.format("parquet").option("path", f"{own}/rows").option("checkpointLocation", f"{own}/state").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(out.schema).parquet(f"{own}/rows")


def tile_totals(stream: DataFrame) -> DataFrame:
    """tile_id, n_part: each tile's particles since the stream began, given anew whenever some arrive; state is one number a tile."""
    import pandas as pd

    def update(key, chunks, state):
        n = (state.get[0] if state.exists else 0) + sum(len(c) for c in chunks)
        state.update((n,))
        yield pd.DataFrame({"tile_id": [key[0]], "n_part": [n]})

    return stream.groupBy("tile_id").applyInPandasWithState(update, "tile_id bigint, n_part bigint", "n bigint", "append", "NoTimeout")


def tile_counts(stream: DataFrame, window: str = "1 day", late: str = "1 day") -> DataFrame:
    """Particles by window and tile; rows later than the watermark are dropped, state is one row a tile and open window."""
    tiles = stream.withWatermark("ts", late).withColumn("tile_id", F.col("user_id").cast("bigint") % 16 + F.least(F.lit(15), F.floor(F.col("value") / 16)) * 16)
    return tiles.groupBy(F.window("ts", window).alias("w"), "tile_id").agg(F.count("*").alias("n_part"))
