"""The multi-index against all pairs: radii, segment counts, full buckets, hot fingerprints."""

import random

import numpy as np
import pytest

from tests.llm.fixtures import documents
from tilebalance.llm import simhash


def made(seed, n_base=10, n_each=14, flips=6, half=0):
    rnd = random.Random(seed)
    prints = set()
    for _ in range(n_base):
        b = rnd.getrandbits(64)
        for _ in range(n_each):
            x = b
            for bit in rnd.sample(range(half, 64), rnd.randrange(0, flips)):
                x ^= 1 << bit
            prints.add(x)
    return sorted(prints | {0, (1 << 64) - 1, 1 << 63})


def roots(n, pairs):
    at = list(range(n))
    moved = True
    while moved:
        moved = False
        for a, b in pairs:
            if at[a] != at[b]:
                at[a] = at[b] = min(at[a], at[b])
                moved = True
    return at


@pytest.mark.parametrize("radius, segments, bucket, half", [(0, 2, 256, 0), (1, 2, 256, 0), (2, 2, 256, 0), (3, 2, 256, 0), (4, 2, 256, 0), (4, 4, 256, 0), (3, 5, 256, 0), (2, 2, 3, 32), (3, 2, 3, 32), (1, 2, 2, 32), (2, 3, 0, 0)])
def test_every_close_pair_is_connected(spark, radius, segments, bucket, half):
    prints = made(radius * 7 + segments, half=half)
    signed = np.array(prints, dtype=np.uint64).view(np.int64).tolist()
    df = spark.createDataFrame(list(zip(signed, range(len(signed)))), "fp bigint, rep bigint")
    got = [(r.a, r.b) for r in simhash.links(df, radius, segments, bucket).collect()]
    assert all(0 < (prints[a] ^ prints[b]).bit_count() <= radius for a, b in got)
    every = [(i, j) for i in range(len(prints)) for j in range(i) if (prints[i] ^ prints[j]).bit_count() <= radius]
    assert roots(len(prints), got) == roots(len(prints), every)
    assert radius == 0 or len(every) > 3


def test_limits(spark):
    df = spark.createDataFrame([], "fp bigint, rep bigint")
    with pytest.raises(ValueError):
        simhash.links(df, 5)
    assert simhash.links(df).count() == 0


@pytest.mark.parametrize("hot", [1, 4, 1000])
def test_hot_fingerprints_change_nothing(spark, hot):
    docs = documents(spark, 80)
    want = sorted(map(str, simhash.near_groups(docs).collect()))
    assert sorted(map(str, simhash.near_groups(docs, hot=hot).collect())) == want and len(want) == docs.count()
