"""Lists of rows to drop leave all other texts where they are."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline


@pytest.fixture
def no_broadcast(spark):
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    yield
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)


def test_only_listed_rows_are_shuffled(spark, no_broadcast):
    docs = spark.range(2000).select(F.col("id").alias("doc_id"), F.concat(F.lit("text "), F.col("id")).alias("text")).union(spark.createDataFrame([(7, None), (None, "text 4"), (None, "z")], "doc_id bigint, text string"))
    gone = docs.where("doc_id % 20 = 0 or doc_id is null").select(F.col("doc_id").alias("_id"), corpus_pipeline.digest(docs).alias("_sha"))
    for listed, stay in ((gone, lambda i, t: i is not None and (i % 20 or t is None)), (gone.select("_sha"), lambda i, t: t is None or t != "z" and int(t[5:]) % 20 and t != "text 4")):
        out = corpus_pipeline.without(docs, listed)
        assert sorted(out.collect(), key=str) == sorted((r for r in docs.collect() if stay(r.doc_id, r.text)), key=str)
        plan = out._jdf.queryExecution().executedPlan().toString().partition("== Initial Plan ==")[0]
        assert "Union" in plan and "BroadcastHashJoin" in plan
