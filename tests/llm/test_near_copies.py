import random

import corpus_pipeline
from tilebalance.llm import near_copies


def brute_groups(texts):
    """Smallest index of each text's group, by the similarity of every pair of 5-word shingle sets."""
    words = [(t or "").encode().lower().split() for t in texts]
    own = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for w in words]
    root = list(range(len(texts)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(own)):
        for j in range(i):
            small, large = sorted((len(own[i]), len(own[j])))
            if small * 5 >= large * 4 and len(own[i] & own[j]) * 5 >= len(own[i] | own[j]) * 4:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(texts))]


def sample(seed=3):
    """Groups at similarities about 0.8 in chains, a large group, a passage many share, short and empty texts."""
    rnd = random.Random(seed)
    new = lambda n: [f"w{rnd.randrange(5000)}" for _ in range(n)]
    texts, passage = [None, " ", "a b", "A  B", "a b c d e", "a b c d e f"], new(40)
    for _ in range(25):
        own = new(rnd.randrange(30, 200))
        for _ in range(6):
            texts.append(" ".join(own))
            own = list(own)
            for _ in range(max(1, len(own) // 50)):
                own[rnd.randrange(len(own))] = f"x{rnd.randrange(9999)}"
    texts += [" ".join(passage + new(40)) for _ in range(80)]
    large = new(120)
    texts += [" ".join(large[:k] + ["y%d" % k] + large[k + 1 :]) for k in range(120)]
    rnd.shuffle(texts)
    return texts


def test_groups_equal_brute_force(spark):
    texts = sample()
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").repartition(5)
    want = {i for i, r in enumerate(brute_groups(texts)) if r == i}
    got = [r.doc_id for r in corpus_pipeline.drop_near_copies(spark, docs, "").collect()]
    assert sorted(got) == sorted(want) and len(want) < len(texts) - 150


def test_near_copies_of_a_table(spark):
    rows = sorted({r.text: r.doc_id for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text").limit(1500).collect()}.items(), key=lambda r: r[1])
    docs = spark.createDataFrame([(i, t) for t, i in rows], "doc_id bigint, text string")
    keep = {rows[i][1] for i, r in enumerate(brute_groups([t for t, _ in rows])) if r == i}
    assert {r.doc_id for r in near_copies.first_of_group(docs).collect()} == keep


def test_rows_that_share_an_id(spark):
    a, b = " ".join(f"a{k}" for k in range(60)), " ".join(f"b{k}" for k in range(60))
    docs = spark.createDataFrame([(None, a), (None, b), (7, a + " more"), (7, b + " x"), (None, b + " y")], "doc_id bigint, text string")
    got = [tuple(r) for r in near_copies.first_of_group(docs).collect()]
    assert sorted(got) == [(7, a + " more"), (7, b + " x")]
    assert near_copies.first_of_group(docs.limit(0)).count() == 0
