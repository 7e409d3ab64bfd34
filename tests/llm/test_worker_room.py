"""A worker that goes on with another operator does not hold the models of the one before."""

import public_tokenizers
import pyarrow as pa
import pytest

from tilebalance.llm import common, decontaminate, near_copies, pieces, simhash, toxicity

KEY = "spark.sql.execution.arrow.maxRecordsPerBatch"


def held(spark):
    """How many piece models the workers hold, the most."""

    def run(batches):
        for _ in batches:
            yield pa.RecordBatch.from_arrays([pa.array([len(models())], pa.int64())], names=["n"])

    models = lambda f=common.kept: f("pieces")
    return max(r.n for r in spark.range(0, 64, 1, 64).mapInArrow(run, "n bigint").collect())


@pytest.mark.parametrize("operator", ["sets", "prefixes", "prints", "scores", "column", "leaks"])
def test_models_of_pieces_are_dropped(spark, operator):
    docs = spark.range(0, 64, 1, 64).selectExpr("id as doc_id", "id as _row", "concat('some words of text number ', id) as text")
    pieces.encode(docs, public_tokenizers.path("piece_bpe_32k.model")).collect()
    assert held(spark) == 1
    field = toxicity.fit(["a b c"], [0], 0.5)
    run = {
        "sets": lambda: near_copies.sets(docs),
        "prefixes": lambda: near_copies.prefixes(docs),
        "prints": lambda: simhash.fingerprints(docs),
        "scores": lambda: toxicity.score_documents(docs, field),
        "column": lambda: docs.select(toxicity.score_column(field)("text")),
        "leaks": lambda: decontaminate.report(docs, docs.selectExpr("doc_id as item_id", "text").limit(3)),
    }[operator]
    assert len(run().collect()) == 64
    assert held(spark) == 0


def test_few_rows_at_once(spark):
    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([batch.num_rows], pa.int64())], names=["n"])

    before = spark.conf.get(KEY)
    sizes = [r.n for r in common.materialise(spark.range(0, 2500, 1, 1).mapInArrow(run, "n bigint"), "sizes").collect()]
    assert max(sizes) <= 1000 and sum(sizes) == 2500
    assert spark.conf.get(KEY) == before
