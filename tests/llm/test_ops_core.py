import hashlib
import random
import re
from collections import defaultdict

import numpy as np
import pytest

from tests.compare import same
from tests.llm.fixtures import documents, empty
from tilebalance.llm import decontaminate, exact_dedup, sharding, simhash, toxicity, url_filter
from tilebalance.llm.common import components
from tilebalance.llm.queries import oracle_sql, queries

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", sorted(oracle_sql()))
def test_against_sql(spark, name):
    same(queries()[name](spark, SF), oracle_sql()[name], SF)


@pytest.mark.parametrize("heavy", [1, 4, 1024])
def test_exact_dedup(spark, heavy):
    docs = documents(spark)
    rows = [(r.doc_id, r.text or "") for r in docs.select("doc_id", "text").collect()]
    groups = defaultdict(list)
    for i, t in rows:
        groups[t].append(i)
    want = sorted((str(i), str(max((x for x in groups[t] if x is not None), default=None)), len(groups[t]), hashlib.sha256(t.encode()).hexdigest()) for i, t in rows)
    got = exact_dedup.exact_dedup(docs, heavy=heavy).collect()
    assert sorted((str(r.doc_id), str(r.keep_id), r.group_size, r.text_sha256) for r in got) == want
    assert all(r.kept == (r.doc_id == r.keep_id) for r in got)
    assert exact_dedup.exact_dedup(empty(spark)).count() == 0


def test_exact_dedup_is_native(spark):
    plan = exact_dedup.exact_dedup(documents(spark))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|ArrowEval", plan)


def test_url_filter(spark):
    urls = {
        1: "https://www.example.com/en/x", 2: "http://Example.COM/en/y", 3: "http://a.example.net/es/", 4: "https://example.org/porn?x", 5: "https://example.org/xporn", 6: "https://example.org/free/win",
        7: "https://example.org/free/free", 8: None, 9: "", 10: "no-scheme.com/xxx", 11: "https://example.com", 12: "https://badexample.com/en/", 13: "ftp://h?q=/a/b#c", 14: "https://x.example.com/en#f",
    }
    df = spark.createDataFrame(list(urls.items()), "page_id int, url string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filter.judge(df).collect()}
    assert got[1] == ("www.example.com", "/en/x", "www.example.com/en/", "allow")
    assert got[2] == ("example.com", "/en/y", "example.com/en/", "block")
    assert got[3][2:] == ("net/es/", "block") and got[4][2:] == (None, "block") and got[5][2:] == (None, "allow")
    assert got[6][3] == "block" and got[7][3] == "allow" and got[8] == ("", "", None, "allow") and got[9][:2] == ("", "")
    assert got[10] == ("", "", None, "block") and got[11][:3] == ("example.com", "", None) and got[12][2] == "com/"
    assert got[13][:2] == ("h", "") and got[14][1:3] == ("/en", "com/")


def brute_fingerprint(text):
    import xxhash

    words = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))
    if not words:
        return 0
    hashes = [xxhash.xxh64_intdigest(b" ".join(words[i : i + 3]), 42) for i in range(max(1, len(words) - 2))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_simhash_groups(spark):
    docs = documents(spark)
    rows = [(r.doc_id, brute_fingerprint(r.text)) for r in docs.collect()]
    parent = {i: i for i, _ in rows}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, f in rows:
        for j, g in rows:
            if i is not None and j is not None and (f ^ g).bit_count() <= 2:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    got = {(r.doc_id, r.fingerprint, r.component_id) for r in simhash.near_groups(docs).collect()}
    assert {x for x in got if x[0] is not None} == {(i, f"{f:016x}", find(i)) for i, f in rows if i is not None}
    assert simhash.near_groups(empty(spark)).count() == 0


def test_simhash_links_of_close_fingerprints(spark):
    rnd = random.Random(5)
    base = [rnd.getrandbits(64) for _ in range(12)]
    prints = set(base)
    for b in base:
        for _ in range(15):
            x = b
            for bit in rnd.sample(range(64), rnd.randrange(1, 5)):
                x ^= 1 << bit
            prints.add(x)
    prints = sorted(prints)
    signed = np.array(prints, dtype=np.uint64).view(np.int64).tolist()
    df = spark.createDataFrame(list(zip(signed, range(len(signed)))), "fp bigint, rep bigint")
    links = [(r.a, r.b) for r in simhash.links(df).collect()]
    assert all((prints[a] ^ prints[b]).bit_count() <= 2 for a, b in links)

    def roots(pairs):
        at = list(range(len(prints)))
        for _ in prints:
            for a, b in pairs:
                at[a] = at[b] = min(at[a], at[b])
        return at

    every = [(i, j) for i in range(len(prints)) for j in range(i) if (prints[i] ^ prints[j]).bit_count() <= 2]
    assert roots(links) == roots(every)


def test_components_of_a_long_chain(spark):
    n = 300
    order = list(range(n))
    random.Random(3).shuffle(order)
    df = spark.createDataFrame([(order[i], order[i + 1]) for i in range(n - 1)] + [(1000, 1001), (7, 7), (None, 3)], "a bigint, b bigint")
    got = {r.id: r.root for r in components(df).collect()}
    assert got == {i: 0 for i in range(n)} | {1000: 1000, 1001: 1000}


def brute_leaks(docs, items, window=10):
    word = lambda t: re.findall(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").encode().lower())
    out = {}
    for d, t in docs:
        ws, hit, found = word(t), set(), set()
        for i, it in items:
            iw = word(it)
            if i is None or not iw:
                continue
            k = min(window, len(iw))
            grams = {tuple(iw[j : j + k]) for j in range(len(iw) - k + 1)}
            for j in range(len(ws) - k + 1):
                if tuple(ws[j : j + k]) in grams:
                    hit.update(range(j, j + k))
                    found.add(str(i))
        out[d] = (len(ws), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest())
    return out


@pytest.mark.parametrize("shard,block", [(50, 40), (1_000_000, 1 << 20)])
def test_decontaminate(spark, shard, block):
    rnd = random.Random(2)
    v = ["one", "two", "Three", "four", "fünf", "six"]
    gen = lambda n: " ".join(rnd.choice(v[:3] if rnd.random() < 0.7 else v) for _ in range(n))
    items = [(i, gen(rnd.choice([2, 5, 10, 12, 30]))) for i in range(14)] + [(3, "four four four"), (20, None), (21, "..."), (None, "one two")]
    docs = [(d, gen(rnd.randrange(0, 80))) for d in range(40)]
    docs += [(50 + k, gen(30) + ", " + (t or "").upper() + "! " + gen(5)) for k, (_, t) in enumerate(items)] + [(90, None), (91, ""), (92, "one")]
    a, b = spark.createDataFrame(docs, "doc_id bigint, text string"), spark.createDataFrame(items, "item_id bigint, text string")
    got = decontaminate.report(a, b, shard_words=shard, block_bytes=block).collect()
    assert {r.doc_id: (r.n_words, r.n_hit, r.n_items, r.items_sha256) for r in got} == brute_leaks(docs, items)
    assert all(r.contaminated == (r.n_hit > 0) for r in got)
    found = {r.doc_id: r for r in decontaminate.find(a, b, shard_words=shard, block_bytes=block).collect()}
    words = {d: decontaminate.words_of(t) for d, t in docs}
    texts = defaultdict(list)
    for i, t in items:
        texts[str(i)].append(decontaminate.words_of(t))
    for d, r in found.items():
        if r.longest:
            own = words[d][r.longest_at : r.longest_at + r.longest]
            assert any(w[r.longest_from : r.longest_from + r.longest] == own for w in texts[r.longest_item])
    assert decontaminate.report(empty(spark), b).count() == 0
    assert decontaminate.report(a, spark.createDataFrame([], "item_id bigint, text string")).where("contaminated").count() == 0


def test_lookup_table():
    names = sharding.shard_names(7)
    table = sharding.lookup_table(names, 101)
    counts = [table.count(k) for k in range(7)]
    assert max(counts) - min(counts) <= 1
    fewer = sharding.lookup_table(names[:-1], 101)
    assert sum(a != b for a, b in zip(table, fewer)) < 2 * counts[6] + 10
    with pytest.raises(ValueError):
        sharding.lookup_table(names, 100)


def test_place(spark):
    docs = documents(spark)
    placed = sharding.place(docs, "doc_id", sharding.shard_names(5), 11)
    table = sharding.lookup_table(sharding.shard_names(5), 11)
    rows = placed.collect()
    assert len(rows) == docs.count()
    for r in rows:
        key = "" if r.doc_id is None else str(r.doc_id)
        slot = int(hashlib.md5(key.encode()).hexdigest()[:15], 16) % 11
        assert (r.slot, r.shard) == (slot, f"shard-{table[slot]:05d}")
    assert not re.search("Python|Pandas|ArrowEval", placed._jdf.queryExecution().executedPlan().toString())
    with pytest.raises(ValueError):
        sharding.place(placed, "doc_id", ["a"], 11)


def test_chain_marginals_against_enumeration():
    rnd = np.random.default_rng(0)
    lengths = np.array([5, 0, 3, 1, *[4] * 20, 7])
    starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    e = np.exp(rnd.normal(size=lengths.sum()))
    trans = (0.3, -0.5, -0.2, 0.8)
    got = toxicity.chain_marginals(e, starts, lengths, trans)
    w = np.exp(trans).reshape(2, 2)
    for a, n in zip(starts, lengths):
        total, one = 0.0, np.zeros(n)
        for bits in range(1 << n):
            y = [bits >> t & 1 for t in range(n)]
            s = np.prod([e[a + t] if y[t] else 1.0 for t in range(n)]) * np.prod([w[y[t], y[t + 1]] for t in range(n - 1)])
            total += s
            one += s * np.array(y)
        assert np.allclose(got[a : a + n], one / total)


def test_toxicity_held_out(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    model = toxicity.train(docs, labels)
    held = docs.join(labels, "doc_id").where(toxicity.held_out(docs.doc_id))
    rows = toxicity.score_documents(held, model, spans=True).join(labels, "doc_id").collect()
    right = sum((r.score >= 0.5) == bool(r.toxic) for r in rows)
    caught = [r for r in rows if r.toxic and r.score >= 0.5]
    assert right / len(rows) > 0.95 and len(caught) / sum(r.toxic for r in rows) > 0.75
    assert sum(bool(r.spans) for r in caught) > 0.9 * len(caught)
    few = toxicity.score_documents(documents(spark), model)
    assert few.count() == documents(spark).count() and few.where("score is null or score < 0 or score > 1").count() == 0
    assert toxicity.score_documents(empty(spark), model).count() == 0
    assert toxicity.train(empty(spark), labels.limit(0)).marginals(["a b", None])[0].shape == (2,)
