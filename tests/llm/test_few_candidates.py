"""Texts that merely share a passage are not compared as whole sets."""

import random

import numpy as np
import pytest

from tilebalance.llm import near_copies

from .test_near_copies import brute_groups


def test_shared_passages_are_not_compared(spark, monkeypatch):
    rnd = random.Random(4)
    new = lambda n: [f"w{rnd.randrange(10**6)}" for _ in range(n)]
    passages = {n: new(n) for n in (60, 1500)}
    texts = [" ".join(p + new(n)) for n, p in passages.items() for _ in range(40)]
    texts += [t + " end" for t in texts[::10]]
    compared = []

    def counting(pairs, *rest, f=near_copies.verified):
        compared.append(pairs.count())
        return f(pairs, *rest)

    monkeypatch.setattr(near_copies, "verified", counting)
    monkeypatch.setattr(near_copies, "SAMPLE_OFTEN", 10**9)  # an order that does not know the passages
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    assert sorted(r.doc_id for r in near_copies.first_of_group(docs).collect()) == [i for i, r in enumerate(brute_groups(texts)) if r == i] == list(range(80))
    assert sum(compared) <= 16


@pytest.mark.parametrize("bits,bits2", [(512, 512), (1024, 512), (2048, 2048)])
def test_parities_differ_no_more_than_sets(bits, bits2):
    rnd = np.random.default_rng(1)
    for n, d in ((500, 0), (500, 40), (1000, 300)):
        common = rnd.integers(0, 1 << 63, n).astype(np.uint64)
        a, b = (np.concatenate([common, rnd.integers(0, 1 << 63, d // 2).astype(np.uint64)]) for _ in range(2))
        x, y = near_copies.parity(a, bits), near_copies.parity(b, bits2)
        x, y = (np.bitwise_xor.reduce(v.reshape(-1, min(len(x), len(y)))) for v in (x, y))
        assert sum(int(v).bit_count() for v in (x ^ y).view(np.uint64)) <= d
        assert (near_copies.parity(a, 512) == np.bitwise_xor.reduce(near_copies.parity(a, bits).reshape(-1, 8))).all()
