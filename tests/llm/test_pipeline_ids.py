"""Each stage decides by row where rows share an id."""

import pytest

import corpus_pipeline

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def texts(spark):
    item = max((r.text for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()), key=len)
    clean = [" ".join(f"{c}{k}" for k in range(50)) for c in "pqrs"]
    return clean, [f"{t} {item} {t}" for t in clean]


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id bigint, text string")


def kept(stage, spark, rows):
    return sorted((tuple(r) for r in stage(spark, frame(spark, rows), SF).collect()), key=str)


@pytest.mark.parametrize("i", [None, 5])
def test_copies(spark, texts, i):
    a, b = texts[0][:2]
    assert kept(corpus_pipeline.drop_copies, spark, [(i, a), (i, b), (9, a)]) == sorted([(i, b), (9, a)], key=str)


@pytest.mark.parametrize("i", [None, 5])
def test_near_copies(spark, texts, i):
    a, b = texts[0][:2]
    assert kept(corpus_pipeline.drop_near_copies, spark, [(i, a + " more"), (i, b), (1, a)]) == sorted([(i, b), (1, a)], key=str)


@pytest.mark.parametrize("i", [None, 5])
def test_contaminated(spark, texts, i):
    clean, leaks = texts
    assert kept(corpus_pipeline.drop_contaminated, spark, [(i, clean[0]), (i, leaks[1]), (i, leaks[2]), (3, clean[3]), (4, leaks[3])]) == sorted([(i, clean[0]), (3, clean[3])], key=str)


@pytest.mark.parametrize("i", [None, 5])
def test_toxic(spark, texts, i):
    rows = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    stays = {r.text for r in corpus_pipeline.drop_toxic(spark, rows, SF).collect()}
    every = [(r.doc_id, r.text) for r in rows.collect()]
    labelled = {r[0] for r in spark.read.parquet(f"{SF}/labels.parquet").select("doc_id").collect()}
    shared = [(d if d in labelled else i, t) for d, t in every]
    got = {t for _, t in kept(corpus_pipeline.drop_toxic, spark, shared)}
    assert got == stays
