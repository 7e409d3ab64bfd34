"""Streams of events; the twins are batch SQL over the same rows."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..streaming import events
from . import query

_DAY = "CAST(date_trunc('day', ts) AS DATE)"
_TILE = "user_id % 16 + least(15, CAST(floor(value / 16) AS BIGINT)) * 16"


@query("st_tumbling", f"SELECT {_DAY} AS day, {_TILE} AS tile_id, count(*) AS n_part FROM events GROUP BY ALL")
def _(spark, d):
    return events.drain(events.tile_counts(events.source(spark, d)), "complete").select(F.to_date("w.start").alias("day"), "tile_id", "n_part")


@query("st_sliding", f"SELECT day, sum(n) AS n FROM (SELECT {_DAY} AS day, count(*) AS n FROM events GROUP BY 1 UNION ALL SELECT {_DAY} - 1, count(*) FROM events GROUP BY 1) GROUP BY day")
def _(spark, d):
    rows = events.source(spark, d).withWatermark("ts", "1 day").groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return events.drain(rows, "complete").select(F.to_date("w.start").alias("day"), "n")


@query("st_session", "SELECT user_id, count(*) AS n_sessions FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events) WHERE p IS NULL OR ts - p >= INTERVAL 6 HOUR GROUP BY 1")
def _(spark, d):
    # Spark joins sessions that just touch: a gap of six hours parts them when each ends a microsecond earlier.
    rows = events.source(spark, d).withWatermark("ts", "1 day").groupBy(F.session_window("ts", "5 hours 59 minutes 59.999999 seconds"), "user_id").agg(F.count("*").alias("n"))
    return events.drain(rows, "complete").groupBy("user_id").agg(F.count("*").alias("n_sessions"))


@query("st_dedup", "SELECT user_id, event_type FROM events GROUP BY ALL")
def _(spark, d):
    rows = events.source(spark, d).withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")
    return events.drain(rows)


@query("st_static_join", f"SELECT pe, count(*) AS n FROM (SELECT ({_TILE}) // 32 AS pe FROM events) GROUP BY 1")
def _(spark, d):
    """Each event meets the map of its tile."""
    maps = spark.range(256).select(F.col("id").alias("tile_id"), F.expr("id div 32").alias("pe"))
    rows = events.source(spark, d).withColumn("tile_id", F.expr("user_id % 16 + least(15, cast(floor(value / 16) AS bigint)) * 16")).join(F.broadcast(maps), "tile_id").groupBy("pe").agg(F.count("*").alias("n"))
    return events.drain(rows, "complete")


@query("st_interval_join", "SELECT count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _(spark, d):
    a = events.source(spark, d).select(F.col("user_id").alias("u"), F.col("ts").alias("ta")).withWatermark("ta", "1 day")
    b = events.source(spark, d).select(F.col("user_id").alias("v"), F.col("ts").alias("tb")).withWatermark("tb", "1 day")
    return events.drain(a.join(b, F.expr("u = v AND tb > ta AND tb <= ta + INTERVAL 1 HOUR"))).agg(F.count("*").alias("n"))


def _batch(spark, d):
    return spark.read.parquet(f"{d}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


@query("st_late", f"SELECT {_DAY} AS day, count(*) AS n FROM events GROUP BY 1 HAVING {_DAY} + 1 <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY")
def _(spark, d):
    """All events, then after a restart the same ones again: days that the watermark has closed are given once and take no late rows."""
    rows = _batch(spark, d).select("ts")
    counts = lambda s: s.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.to_date("w.start").alias("day"), "n")
    return events.replay([rows, rows], counts)


@query("st_tile_state", f"SELECT {_TILE} AS tile_id, count(*) AS n_part FROM events GROUP BY 1")
def _(spark, d):
    """Totals of tiles held in state over a restart: half of the events before it, half after."""
    rows = _batch(spark, d).selectExpr("event_id", "cast(user_id % 16 + least(15, cast(floor(value / 16) AS bigint)) * 16 AS bigint) AS tile_id")
    parts = [rows.where(F.col("event_id") % 2 == k) for k in (0, 1)]
    return events.replay(parts, lambda s: events.tile_totals(s.select("tile_id"))).groupBy("tile_id").agg(F.max("n_part").alias("n_part"))


@query("st_rebalance")
def _(spark, d):
    """Each batch's counts make a new map of 8 groups; the imbalance of each batch under its map."""
    from .. import decomp, metrics
    from ..lattice import Domain
    from ..load import load_array

    dom, found = Domain((16, 16), (1, 1), order=0), []

    def act(batch, number):
        cells = batch.selectExpr(f"{number} AS step", "user_id % 16 AS cx", "least(15, cast(floor(value / 16) AS bigint)) AS cy")
        load = load_array(cells, dom)
        found.extend(metrics.imbalance(decomp.decompose(load, dom, 8, "hilbert"), 8).collect())  # one row a batch

    events.each_batch(events.source(spark, d), act)
    return spark.createDataFrame([(r.step, float(r.imbalance)) for r in found], "batch int, imbalance double")
