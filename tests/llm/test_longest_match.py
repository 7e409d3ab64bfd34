"""Longest verbatim matches of any length against all pairs of places."""

import random

import numpy as np
import pytest

from tilebalance.llm import decontaminate


def brute(words, items):
    """(length, place) of the longest run of words that some item has."""
    best = (0, 0)
    for a in range(len(words)):
        for own in items:
            for b in range(len(own)):
                k = 0
                while a + k < len(words) and b + k < len(own) and words[a + k] == own[b + k]:
                    k += 1
                if k > best[0]:
                    best = (k, a)
    return best


@pytest.mark.parametrize("seed, n_words", [(1, 3), (2, 12), (3, 400), (4, 40_000)])
def test_longest_runs(seed, n_words):
    rnd = random.Random(seed)
    word = lambda: f"w{rnd.randrange(n_words)}"
    items = [[word() for _ in range(rnd.choice([1, 4, 9, 25]))] for _ in range(20)] + [[f"only{k}" for k in range(n_words // 3)]]
    docs = [[word() for _ in range(rnd.randrange(0, 50))] for _ in range(40)]
    docs += [[word() for _ in range(6)] + own[i : i + k] + ["zz"] + [word() for _ in range(6)] for own in items[:20] for i, k in [(0, 3), (1, 9), (0, 30)]]
    queries = decontaminate.Queries.of([(f"{k:03}", " ".join(own)) for k, own in enumerate(items)], 10)
    found = decontaminate.search_shard([" ".join(d) for d in docs], queries)
    for own, r in zip(docs, found):
        n, at = brute(own, items[:20])
        assert r["longest"] == n
        if n:
            assert r["longest_at"] == at
            src = items[int(r["longest_item"])]
            assert src[r["longest_from"] : r["longest_from"] + n] == own[at : at + n]
            assert not any(own[at : at + n] == x[j : j + n] for x in items[: int(r["longest_item"])] for j in range(len(x)))


def test_nine_shared_words_are_a_longest_match_and_no_hit(spark):
    item = " ".join(f"q{k}" for k in range(20))
    docs = spark.createDataFrame([(1, "a b " + " ".join(f"q{k}" for k in range(3, 12)) + " c"), (2, "a b c")], "doc_id bigint, text string")
    bench = spark.createDataFrame([(7, item)], "item_id bigint, text string")
    for size in (1 << 20, 8):
        got = {r.doc_id: r for r in decontaminate.find(docs, bench, block_bytes=size).collect()}
        assert (got[1].longest, got[1].longest_item, got[1].longest_at, got[1].longest_from, got[1].n_hit) == (9, "7", 2, 3, 0)
        assert (got[2].longest, got[2].longest_item, got[2].items) == (0, None, [])


def test_blocks_agree(spark):
    rnd = random.Random(9)
    gen = lambda n: " ".join(rnd.choice("abcdefgh") for _ in range(n))
    bench = spark.createDataFrame([(i, gen(rnd.choice([3, 12, 40]))) for i in range(30)], "item_id bigint, text string")
    docs = spark.createDataFrame([(i, gen(rnd.randrange(0, 200))) for i in range(50)] + [(None, gen(30)), (None, None), (3, gen(40))], "doc_id bigint, text string")
    one, many = (sorted(map(str, decontaminate.find(docs, bench, block_bytes=b).collect())) for b in (1 << 20, 100))
    assert one == many and len(one) == 53
