import corpus_pipeline
from tests.llm.test_ops_core import brute_fingerprint, brute_leaks
from tilebalance.llm import toxicity


def test_pipeline_against_brute_force(spark):
    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    model = toxicity.train(docs, spark.read.parquet(f"{d}/labels.parquet"))
    rows = {r.doc_id: r.text for r in docs.collect()}
    kept = {i: t for i, t in rows.items() if model.score(model.marginals([t])[0]) < corpus_pipeline.TOXIC_FROM}
    last = {t: i for i, t in sorted(kept.items())}
    kept = {i: t for i, t in kept.items() if last[t] == i}
    prints = {i: brute_fingerprint(t) for i, t in kept.items()}
    root = {i: i for i in kept}
    for _ in kept:
        for i in kept:
            root[i] = min(root[j] for j in kept if (prints[i] ^ prints[j]).bit_count() <= 2)
        if all(root[root[i]] == root[i] for i in kept):
            break
    kept = {i: t for i, t in kept.items() if root[i] == i}
    leaks = brute_leaks(list(kept.items()), [(r.item_id, r.text) for r in spark.read.parquet(f"{d}/benchmark.parquet").collect()])
    kept = {i: t for i, t in kept.items() if not leaks[i][1]}
    import hashlib

    got = {r.doc_id: r.decoded_sha256 for r in corpus_pipeline.run(spark, d).collect()}
    assert got == {i: hashlib.sha256(t.encode()).hexdigest() for i, t in kept.items()}
    assert 0 < len(got) < len(rows)


def test_stages_keep_columns(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, "/root/testdata/sf0.001").columns == docs.columns
