"""The relational surface around the methods: one small query for each kind of operator, on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..views import VIEWS
from . import query, twins


def t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def views(spark: SparkSession, d: str, *names: str) -> None:
    for n in names:
        t(spark, d, n).createOrReplaceTempView(n)


def both(name: str, sql: str, tables: str, spark_sql: str | None = None) -> None:
    """Queries whose text both engines read."""

    def run(spark, d):
        views(spark, d, *tables.split())
        return spark.sql(spark_sql or sql)

    query(name, sql)(run)


# Projection, filters, conditions.
query("op_scan_project", "SELECT o_orderkey, o_custkey % 10 AS bucket, CAST(floor(o_totalprice) AS BIGINT) AS price FROM orders")(lambda s, d: t(s, d, "orders").selectExpr("o_orderkey", "o_custkey % 10 AS bucket", "cast(floor(o_totalprice) AS bigint) AS price"))
query("op_filter", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_linestatus LIKE 'F%' AND NOT l_discount > 0.05")(
    lambda s, d: t(s, d, "lineitem").where(F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R") & F.col("l_linestatus").like("F%") & ~(F.col("l_discount") > 0.05)).select("l_orderkey", "l_linenumber", "l_quantity")
)
query("op_case", "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'low' ELSE 'high' END AS band, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS segment, greatest(c_nationkey, 5) AS g, least(c_nationkey, 5) AS l FROM customer")(
    lambda s, d: t(s, d, "customer").select("c_custkey", F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 5000, "low").otherwise("high").alias("band"), F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("none")).alias("segment"), F.greatest("c_nationkey", F.lit(5)).alias("g"), F.least("c_nationkey", F.lit(5)).alias("l"))
)

# Joins.
for _kind, _sql in (("inner", "JOIN"), ("left", "LEFT JOIN"), ("right", "RIGHT JOIN"), ("full", "FULL JOIN")):
    query(f"op_join_{_kind}", f"SELECT c_nationkey, n_name, count(*) AS n FROM (SELECT c_nationkey FROM customer WHERE c_nationkey < 15) c {_sql} (SELECT * FROM nation WHERE n_nationkey > 5) x ON c_nationkey = n_nationkey GROUP BY ALL")(
        lambda s, d, k=_kind: t(s, d, "customer").where("c_nationkey < 15").join(t(s, d, "nation").where("n_nationkey > 5"), F.col("c_nationkey") == F.col("n_nationkey"), k).groupBy("c_nationkey", "n_name").agg(F.count("*").alias("n"))
    )
query("op_join_semi", "SELECT doc_id, n_chars FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")(lambda s, d: t(s, d, "documents").join(t(s, d, "labels").where("quality = 1"), "doc_id", "left_semi").select("doc_id", "n_chars"))
query("op_join_anti", "SELECT doc_id, n_chars FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")(lambda s, d: t(s, d, "documents").join(t(s, d, "labels"), "doc_id", "left_anti").select("doc_id", "n_chars"))
query("op_join_cross", "SELECT n_name, r_name FROM nation, region")(lambda s, d: t(s, d, "nation").crossJoin(F.broadcast(t(s, d, "region"))).select("n_name", "r_name"))
query("op_join_range", "SELECT k, count(*) AS n FROM (SELECT range AS k, range * 50.0 AS lo, range * 50.0 + 50 AS hi FROM range(10)) b JOIN events ON value >= lo AND value < hi GROUP BY k")(
    lambda s, d: t(s, d, "events").join(F.broadcast(s.range(10).select(F.col("id").alias("k"), (F.col("id") * 50.0).alias("lo"), (F.col("id") * 50.0 + 50).alias("hi"))), F.expr("value >= lo and value < hi")).groupBy("k").agg(F.count("*").alias("n"))
)


@query("op_join_asof", "SELECT event_id, m.epoch FROM events e ASOF JOIN (SELECT TIMESTAMP '2024-01-01' + INTERVAL 5 DAY * range AS ts, range AS epoch FROM range(7)) m ON e.ts >= m.ts")
def _(spark, d):
    """The last map at or before each event: a union and a running last value, no range join."""
    maps = spark.range(7).select(F.expr("timestamp_ntz'2024-01-01 00:00:00' + make_dt_interval(cast(5 * id AS int))").alias("ts"), F.lit(None).cast("bigint").alias("event_id"), F.col("id").alias("epoch"))
    rows = t(spark, d, "events").select("ts", "event_id", F.lit(None).cast("bigint").alias("epoch")).unionByName(maps)
    w = Window.orderBy("ts", F.col("event_id").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("epoch", F.last("epoch", ignorenulls=True).over(w)).where("event_id is not null").select("event_id", "epoch")


both("op_join_lateral", "SELECT n_nationkey, x.k FROM nation, LATERAL (SELECT n_nationkey * 2 AS k) x", "nation")
query("op_join_self", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON b.s_suppkey = a.s_suppkey + 1")(lambda s, d: t(s, d, "supplier").select(F.col("s_suppkey").alias("a"), (F.col("s_suppkey") + 1).alias("b")).join(t(s, d, "supplier").select(F.col("s_suppkey").alias("b")), "b"))
for _hint in ("broadcast", "merge", "shuffle_hash"):
    query(f"op_join_{_hint}", "SELECT o_orderstatus, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")(
        lambda s, d, h=_hint: t(s, d, "orders").join(t(s, d, "customer").select("c_custkey").hint(h), F.col("o_custkey") == F.col("c_custkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"))
    )
query("op_join_nullsafe", "SELECT count(*) AS n FROM (SELECT CASE WHEN c_nationkey > 3 THEN c_nationkey END AS k FROM customer) a JOIN (SELECT CASE WHEN n_nationkey > 3 THEN n_nationkey END AS k FROM nation) b ON a.k IS NOT DISTINCT FROM b.k")(
    lambda s, d: t(s, d, "customer").select(F.expr("case when c_nationkey > 3 then c_nationkey end").alias("k")).alias("a").join(t(s, d, "nation").select(F.expr("case when n_nationkey > 3 then n_nationkey end").alias("k")).alias("b"), F.expr("a.k <=> b.k")).agg(F.count("*").alias("n"))
)

# Aggregates.
both("op_agg_basic", "SELECT l_returnflag, count(*) AS n, sum(CAST(l_quantity AS BIGINT)) AS s, min(l_quantity) AS lo, max(l_quantity) AS hi, round(avg(l_quantity), 4) AS mean, round(stddev(l_quantity), 4) AS sd FROM lineitem GROUP BY l_returnflag", "lineitem")
both("op_agg_distinct", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS n FROM lineitem GROUP BY l_returnflag", "lineitem")
query("op_agg_approx", "SELECT TRUE AS near")(lambda s, d: t(s, d, "lineitem").agg((F.abs(F.approx_count_distinct("l_partkey", 0.02) - F.countDistinct("l_partkey")) <= 0.1 * F.countDistinct("l_partkey")).alias("near")))
both("op_agg_percentile", "SELECT round(median(value), 4) AS m FROM events", "events")
both("op_agg_minmax_by", "SELECT o_orderstatus, max_by(o_orderkey, o_totalprice * 1000000 + o_orderkey) AS top, min_by(o_orderkey, o_totalprice * 1000000 + o_orderkey) AS low FROM orders GROUP BY 1", "orders")
query("op_agg_collect", "SELECT n_regionkey, list_sort(list(n_name)) AS names FROM nation GROUP BY 1")(lambda s, d: t(s, d, "nation").groupBy("n_regionkey").agg(F.array_sort(F.collect_list("n_name")).alias("names")))
both("op_agg_filtered", "SELECT count(*) FILTER (WHERE value > 50) AS n, bool_or(value > 400) AS big FROM events", "events")

# Several levels of grouping.
both("op_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)", "lineitem")
both("op_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)", "lineitem")
both("op_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))", "lineitem")
query("op_pivot", "SELECT l_linenumber, count(*) FILTER (l_returnflag = 'A') AS a, count(*) FILTER (l_returnflag = 'N') AS n, count(*) FILTER (l_returnflag = 'R') AS r FROM lineitem GROUP BY 1")(
    lambda s, d: t(s, d, "lineitem").groupBy("l_linenumber").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count(F.lit(1))).na.fill(0).selectExpr("l_linenumber", "A AS a", "N AS n", "R AS r")
)
query("op_unpivot", "SELECT doc_id, 'quality' AS k, quality AS v FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")(lambda s, d: t(s, d, "labels").unpivot("doc_id", ["quality", "toxic"], "k", "v"))

# Windows.
both("op_win_rank", "SELECT s_suppkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey), v AS (PARTITION BY s_nationkey ORDER BY s_acctbal)", "supplier")
both("op_win_ntile", "SELECT p_partkey, ntile(7) OVER (ORDER BY p_retailprice, p_partkey) AS g FROM part", "part")
both("op_win_laglead", "SELECT event_id, lag(value) OVER w AS before, lead(value, 2) OVER w AS later FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)", "events")
both("op_win_nth", "SELECT event_id, first_value(value) OVER w AS f, nth_value(value, 2) OVER w AS s FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)", "events")
both("op_win_prefix", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 4) AS s FROM events", "events")
both("op_win_sliding", "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 3 PRECEDING AND 1 FOLLOWING) AS m FROM events", "events")
both("op_win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND CURRENT ROW) AS n FROM events", "events")

# Order and set operations.
both("op_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25", "orders")
both("op_limit_offset", "SELECT c_custkey FROM customer ORDER BY c_custkey LIMIT 10 OFFSET 30", "customer")
both("op_topk_per_group", "SELECT * FROM (SELECT s_nationkey, s_suppkey, row_number() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS r FROM supplier) x WHERE r <= 2", "supplier")
query("op_sort", "SELECT n_nationkey, n_name FROM nation")(lambda s, d: t(s, d, "nation").select("n_nationkey", "n_name").orderBy(F.desc("n_name")))
query("op_union", "SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier")(lambda s, d: t(s, d, "customer").select(F.col("c_nationkey").alias("k")).union(t(s, d, "supplier").select("s_nationkey")))
query("op_union_by_name", "SELECT c_nationkey AS k, NULL AS s FROM customer UNION ALL SELECT s_nationkey, s_suppkey FROM supplier")(lambda s, d: t(s, d, "customer").select(F.col("c_nationkey").alias("k")).unionByName(t(s, d, "supplier").select(F.col("s_nationkey").alias("k"), F.col("s_suppkey").alias("s")), allowMissingColumns=True))
both("op_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier", "customer supplier")
both("op_except", "SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier", "nation supplier")
both("op_distinct", "SELECT DISTINCT event_type, user_id % 5 AS u FROM events", "events")

# Functions.
query("op_string", "SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host, upper(substr(url, 1, 5)) AS up, length(url) AS n, lpad(CAST(page_id AS VARCHAR), 8, '0') AS id, replace(url, '/', '|') AS r, levenshtein(substr(url, 1, 12), 'https://abcd') AS lev FROM pages")(
    lambda s, d: t(s, d, "pages").select("page_id", F.regexp_extract("url", "://([^/]+)", 1).alias("host"), F.upper(F.substring("url", 1, 5)).alias("up"), F.length("url").alias("n"), F.lpad(F.col("page_id").cast("string"), 8, "0").alias("id"), F.replace("url", F.lit("/"), F.lit("|")).alias("r"), F.levenshtein(F.substring("url", 1, 12), F.lit("https://abcd")).alias("lev"))
)
query("op_date", "SELECT event_id, CAST(date_trunc('day', ts) AS DATE) AS day, extract(hour FROM ts) AS h, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS n FROM events")(
    lambda s, d: t(s, d, "events").select("event_id", F.to_date("ts").alias("day"), F.expr("extract(hour from ts)").alias("h"), F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).alias("n"))
)
# Spark's floor and ceil give longs, which hold no infinity and no large number; its log2 gives null for what has no logarithm;
# its round goes by a number's decimal digits, that of the SQL by the scaled number, which differ near ties.
_WHOLE = "CASE WHEN value = 0 OR abs(value) >= 4503599627370496 THEN value ELSE CAST({}(value) AS DOUBLE) END"
_NEAR = "CASE WHEN abs({0}) < 1e300 THEN round({0} * 1e{1}, 0) / 1e{1} ELSE {0} END"
_LOG2 = "CASE WHEN value = 0 THEN double('-Infinity') WHEN value < 0 THEN double('NaN') ELSE log2(value) END"
both(
    "op_math", "SELECT event_id, floor(value) AS f, ceil(value) AS c, round(sqrt(value), 6) AS r, round(power(value, 1.5), 3) AS p, round(log2(value), 6) AS l, round(sin(value), 6) AS s FROM events", "events",
    f"SELECT event_id, {_WHOLE.format('floor')} AS f, {_WHOLE.format('ceil')} AS c, {_NEAR.format('sqrt(value)', 6)} AS r, {_NEAR.format('power(value, 1.5)', 3)} AS p, {_NEAR.format(_LOG2, 6)} AS l, {_NEAR.format('sin(value)', 6)} AS s FROM events",
)
query("op_bitwise", "SELECT o_orderkey, o_orderkey & 255 AS a, o_orderkey | 7 AS o, xor(o_orderkey, 21) AS x, o_orderkey << 2 AS l, o_orderkey >> 1 AS r, bit_count(o_orderkey) AS n FROM orders")(
    lambda s, d: t(s, d, "orders").selectExpr("o_orderkey", "o_orderkey & 255 AS a", "o_orderkey | 7 AS o", "o_orderkey ^ 21 AS x", "shiftleft(o_orderkey, 2) AS l", "shiftright(o_orderkey, 1) AS r", "bit_count(o_orderkey) AS n")
)
query("op_array", "SELECT vec_id, len(embedding) AS n, round(CAST(embedding[1] AS DOUBLE), 5) AS a, list_position(list_sort(embedding), list_min(embedding)) AS p FROM embeddings")(lambda s, d: t(s, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.round(F.col("embedding")[0].cast("double"), 5).alias("a"), F.array_position(F.array_sort("embedding"), F.array_min("embedding")).alias("p")))
query("op_hof", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 4) AS norm2, len(list_filter(embedding, lambda x: x > 0)) AS pos FROM embeddings")(
    lambda s, d: t(s, d, "embeddings").select("vec_id", F.round(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x), F.lit(0.0), lambda a, x: a + x), 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"))
)
query("op_map", "SELECT user_id, count(*) AS n_types FROM (SELECT DISTINCT user_id, event_type FROM events) GROUP BY 1")(
    lambda s, d: t(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m")).select("user_id", F.size(F.map_keys(F.map_filter("m", lambda k, v: v > 0))).alias("n_types"))
)
query("op_struct", "SELECT n_nationkey, n_name AS name, n_regionkey AS region FROM nation")(lambda s, d: t(s, d, "nation").select("n_nationkey", F.struct(F.col("n_name").alias("name"), F.col("n_regionkey").alias("region")).alias("x")).select("n_nationkey", "x.*"))
query("op_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")(lambda s, d: t(s, d, "events").select("event_id", F.from_json("props", "k bigint").getField("k").alias("k")))
query("op_variant", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")(lambda s, d: t(s, d, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k")))

# Sampling, recursion, surfaces.
query("op_sample_mod", "SELECT 16 * count(*) AS estimate, (SELECT count(*) FROM lineitem) AS n FROM lineitem WHERE l_orderkey % 16 = 3")(lambda s, d: t(s, d, "lineitem").agg((F.count_if(F.col("l_orderkey") % 16 == 3) * 16).alias("estimate"), F.count("*").alias("n")))
both("op_recursive_cte", "WITH RECURSIVE r AS (SELECT 1 AS k, 1 AS f UNION ALL SELECT k + 1, f * 2 FROM r WHERE k < 20) SELECT k, f FROM r", "nation")


@query("op_sql_surface", twins.with_(twins.load(VIEWS["w7"])) + "SELECT tx, ty, load_u FROM load WHERE step = 50")
def _(spark, d):
    """The load of the disc as one SQL text over views: equal rows to load_array (tested)."""
    views(spark, d, "lineitem", "part", "orders")
    return spark.sql(
        "WITH b AS (SELECT l_partkey * 2000 div (SELECT count(*) FROM part) AS u, l_orderkey * 2000 div (SELECT count(*) FROM orders) AS v FROM lineitem), "
        "p AS (SELECT (30000 + u * 50) div 10000 AS tx, (30000 + v * 50) div 10000 AS ty FROM b WHERE (u - 1000) * (u - 1000) + (v - 1000) * (v - 1000) <= 1000000), "
        "c AS (SELECT tx, ty, count(*) AS n FROM p GROUP BY tx, ty) "
        "SELECT CAST(id % 16 AS int) AS tx, CAST(id div 16 AS int) AS ty, coalesce(n, 0) + 200 AS load_u FROM range(256) LEFT JOIN c ON tx = id % 16 AND ty = id div 16"
    )


query("op_cache_plan", "SELECT o_orderstatus, count(*) AS n FROM orders GROUP BY 1")(lambda s, d: t(s, d, "orders").select("o_orderstatus").repartition(4).coalesce(2).hint("rebalance").groupBy("o_orderstatus").agg(F.count("*").alias("n")))

# Sources and sinks: files are written to the folder all executors share.
for _fmt in ("csv", "json", "orc"):

    @query(f"op_src_{_fmt}", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
    def _(spark, d, fmt=_fmt):
        from ..sources.files import scratch

        path = scratch(spark, fmt)
        df = t(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey")
        df.write.format(fmt).option("header", "true").save(path)
        return spark.read.format(fmt).schema(df.schema).option("header", "true").load(path)


@query("op_src_python", "SELECT CAST(i % 16 AS INTEGER) AS tx, CAST(i // 16 AS INTEGER) AS ty, i AS tile_id FROM generate_series(0, 127) g(i)")
def _(spark, d):
    from ..sources.lattice_source import LatticeSource

    spark.dataSource.register(LatticeSource)
    return spark.read.format("tile_lattice").option("nx", "16").option("ny", "8").load()


@query("op_sink_partitioned", "SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_orderstatus = 'F' GROUP BY 1")
def _(spark, d):
    from ..sources.files import scratch

    path = scratch(spark, "parted")
    t(spark, d, "orders").select("o_orderkey", "o_orderstatus").repartition("o_orderstatus").sortWithinPartitions("o_orderkey").write.partitionBy("o_orderstatus").parquet(path)
    return spark.read.parquet(path).where("o_orderstatus = 'F'").groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@query("op_sink_bucketed", "SELECT o_orderstatus, count(*) AS n, sum(c_nationkey) AS s FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def _(spark, d):
    """Both sides are written in buckets of the join key, so their join needs no exchange."""
    from uuid import uuid4

    from ..sources.files import scratch

    sides = []
    for table, key, *more in (("orders", "o_custkey", "o_orderstatus"), ("customer", "c_custkey", "c_nationkey")):
        name = f"bucketed_{table}_{uuid4().hex}"
        t(spark, d, table).select(key, *more).repartition(8, key).write.bucketBy(8, key).sortBy(key).option("path", scratch(spark, name)).saveAsTable(name)
        sides.append(spark.table(name))
    return sides[0].join(sides[1].hint("merge"), F.col("o_custkey") == F.col("c_custkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum("c_nationkey").alias("s"))


# Functions of one's own.
@query("udf_scalar", "SELECT o_orderkey, least(9, o_orderkey // 100) AS pe FROM orders")
def _(spark, d):
    """Binary search of cut keys in Arrow batches: the form of the map for very many groups."""
    from ..functions.udfs import group_of

    return t(spark, d, "orders").select("o_orderkey", group_of([k * 100 for k in range(10)])(F.col("o_orderkey")).cast("bigint").alias("pe"))


@query("udf_agg", "SELECT user_id, round(max(value) - min(value), 4) AS spread FROM events GROUP BY 1")
def _(spark, d):
    from ..functions.udfs import spread

    return t(spark, d, "events").groupBy("user_id").agg(F.round(spread()("value"), 4).alias("spread"))


@query("udf_table", "SELECT CAST(i % 4 AS INTEGER) AS tx, CAST(i // 4 AS INTEGER) AS ty FROM generate_series(0, 11) g(i)")
def _(spark, d):
    from ..functions.udfs import Lattice

    return Lattice(F.lit(4), F.lit(3))


@query("udf_sql", "SELECT o_orderkey, o_custkey // 8 AS tile FROM orders")
def _(spark, d):
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tile_of(k BIGINT, side BIGINT) RETURNS BIGINT RETURN k div side")
    views(spark, d, "orders")
    return spark.sql("SELECT o_orderkey, tile_of(o_custkey, 8) AS tile FROM orders")


@query("udf_apply", "SELECT user_id, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    import pandas as pd

    return t(spark, d, "events").select("user_id", "value").groupBy("user_id").applyInPandas(lambda key, rows: pd.DataFrame({"user_id": [key[0]], "n": [len(rows)]}), "user_id bigint, n bigint")
