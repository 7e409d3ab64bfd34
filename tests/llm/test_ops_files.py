import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from tests.llm.fixtures import documents, empty
from tilebalance.llm import repair, warc
from tilebalance.llm.common import fresh_path

VOCABULARY = public_tokenizers.path("word_bpe_49k.json")


def brute_rows(rows):
    tk = Tokenizer.from_file(VOCABULARY)
    out, start = {}, 0
    for i, t in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0)):
        ids = tk.encode(t or "", add_special_tokens=False).ids + [2]
        out.setdefault(i, []).append((start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    return {k: sorted(v) for k, v in out.items()}


@pytest.mark.parametrize("tokens,parts", [(1 << 20, 3), (50, 5)])
def test_repair_round_trip(spark, tokens, parts):
    docs = documents(spark)
    rows = [(r.doc_id, r.text) for r in docs.collect()] + [(900, "İstanbul ΑΣ <|endoftext|> it's\x1fok x don't"), (-5, "negative id"), (901, "é é Ǆ ẞ ﬁ")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = {}
    for r in repair.round_trip(df, VOCABULARY, shard_tokens=tokens, parts=parts).collect():
        got.setdefault(r.doc_id, []).append((r.start, r.n_tokens, r.ids_crc32))
    assert {k: sorted(v) for k, v in got.items()} == brute_rows(rows)
    assert repair.round_trip(empty(spark), VOCABULARY).count() == 0


def test_repair_matches_library_on_a_table(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    got = {r.doc_id: [(r.start, r.n_tokens, r.ids_crc32)] for r in repair.round_trip(docs, VOCABULARY).collect()}
    assert got == brute_rows(rows)


def test_grammar_random_access():
    rnd = np.random.default_rng(1)
    docs = [rnd.integers(0, 6, rnd.integers(1, 400)) for _ in range(60)] + [np.array([5]), np.full(300, 3), np.tile([1, 2, 3], 200)]
    blob = repair.pack(list(range(len(docs))), [0] * len(docs), docs, 10)
    shard = repair.Shard(blob)
    assert (shard.all_ids() == np.concatenate(docs)).all()
    assert len(shard.left) > 20 and len(shard.symbols) < 0.6 * sum(map(len, docs))
    for d, own in enumerate(docs):
        assert shard.ids(d) == own.tolist()
        a, b = sorted(rnd.integers(0, len(own) + 1, 2))
        assert shard.ids(d, int(a), int(b)) == own[a:b].tolist()
    with pytest.raises(ValueError):
        repair.Shard(b"nope")


def test_pointer_jumping():
    rnd = random.Random(4)
    at = sorted(rnd.sample(range(1, 5000), 400))
    true = [0] + sorted(rnd.sample(at, 150))
    every = sorted(set(at) | {0})
    nxt = {a: b for a, b in zip(true, true[1:] + [6000])}
    following = [nxt.get(a, rnd.choice(every + [7000])) for a in every]
    got = warc.jump(np.array(every), np.array(following))
    assert [a for a, g in zip(every, got) if g] == true
    loop = warc.jump(np.array([0, 10, 20]), np.array([10, 0, 5]))
    assert loop.tolist() == [True, True, False]


def pages(spark):
    evil = "WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <urn:page:777>\r\nContent-Length: 3\r\n\r\nabc\r\n\r\n"
    long = "<p>" + "x" * 300
    rows = [(1, "http://a/", long), (2, "http://b/", long), (3, None, None), (4, "http://c/\r\nX: y", ""), (5, "u", evil), (6, "u", evil * 40), (7, "u", long), (8, "u", evil + "tail"), (9, "u", "short"), (10, "u", "short"), (11, "é", "ñ" * 99), (12, "u", evil * 40), (12, "u", "again")]
    return spark.createDataFrame([(*r, "x") for r in rows], "page_id bigint, url string, html string, kind string")


@pytest.mark.parametrize("compression", ["gzip", "none"])
def test_warc_rejects_magic_in_payloads(spark, compression):
    df = pages(spark)
    rows = [(r.page_id, (r.html or "").encode()) for r in df.collect()]
    first = {}
    for i, p in rows:
        first[p] = min(i, first.get(p, i))
    want = sorted((i, len(p), hashlib.sha256(p).hexdigest(), *(("revisit", first[p]) if len(p) >= 100 and first[p] != i else ("response", None))) for i, p in rows)
    old = spark.conf.get("spark.sql.files.maxPartitionBytes")
    spark.conf.set("spark.sql.files.maxPartitionBytes", "700b")
    try:
        got = warc.round_trip(df.coalesce(2), compression=compression).drop("file", "offset").collect()
    finally:
        spark.conf.set("spark.sql.files.maxPartitionBytes", old)
    assert sorted(map(tuple, got), key=str) == sorted(want, key=str)
    assert warc.round_trip(df.limit(0)).count() == 0


def test_warc_truncated_file(spark, tmp_path):
    path = fresh_path(spark, "cut")
    warc.write(pages(spark).coalesce(1), path, compression="none")
    import glob

    name = glob.glob(path.removeprefix("file://") + "/part-*")[0]
    data = open(name, "rb").read()
    assert data.startswith(b"WARC/1.1\r\n") and data.endswith(b"\r\n\r\n")
    (tmp_path / "w").mkdir()
    (tmp_path / "w" / "x.warc").write_bytes(data[:-2])
    got = warc.read(spark, str(tmp_path / "w")).collect()
    assert sum(not r.complete for r in got) == 1 and len(got) == 13


def test_remembered_words_equal_the_library_on_odd_texts():
    own = repair.Encoder.at(VOCABULARY)
    for text in [
        "<|endoftext|>x, <|ENDOFTEXT|>. A<|startoftext|>", "É, ŠKODA, İstanbul. naïve! it's, IT'S. 'S, a1. ½, x½. ª. º, ß. a|b, |, | |.", "word,, a_. _, ΣΑΣ. don't. 10.000, a\x1cb. c\x85d",
        ".,", ",", "", " \n", "中文。日本語, abc, Abc, ABC", "À, é. Ñ œuvre; ŀ: þ?",
    ]:
        assert np.frombuffer(own.encode([text])[0], own.kind).tolist() == own.ids(text)
