import numpy as np
import pytest

from tilebalance.llm import repair


def frequent(shard):
    """The most uses of a pair of neighbouring symbols of the shard, places that overlap counted once."""
    uses, until = {}, {}
    for a, b in zip(shard.begin[:-1].tolist(), shard.begin[1:].tolist()):
        for k in range(a, b - 1):
            pair = (int(shard.symbols[k]), int(shard.symbols[k + 1]))
            if until.get(pair, -1) < k:
                uses[pair], until[pair] = uses.get(pair, 0) + 1, k + 1
    return max(uses.values(), default=0)


def cases():
    rnd = np.random.default_rng(2)
    page = rnd.permutation(500)
    yield "run", [np.full(100_000, 7)], 40
    yield "copies", [np.append(page, 500)] * 1000, 1020
    yield "copies in one document", [np.tile(page, 300)], 60
    yield "mixed", [rnd.integers(0, 9, rnd.integers(1, 500)) for _ in range(60)] + [np.full(n, 3) for n in (1, 2, 3, 7, 8, 9, 300)] + [np.tile([1, 2, 3], 200), np.tile([1, 1, 2], 99)], 9000
    yield "words", [(600 * rnd.random(rnd.integers(1, 700)) ** 4).astype(np.int64) for _ in range(150)], 1 << 20


@pytest.mark.parametrize("name,docs,most", list(cases()), ids=[c[0] for c in cases()])
@pytest.mark.parametrize("bits", [8, 18])
def test_no_pair_stays_frequent(name, docs, most, bits):
    shard = repair.Shard(repair.pack(list(range(len(docs))), [0] * len(docs), docs, 1000, bits=bits))
    assert (shard.all_ids() == np.concatenate(docs)).all()
    assert frequent(shard) < repair.MIN_USES
    assert len(shard.symbols) <= most
