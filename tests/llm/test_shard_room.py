"""Memory of the search of one shard, and its results whatever the slice."""

import random
import tracemalloc

from tilebalance.llm import decontaminate
from tilebalance.llm.common import shrink


def made(seed, words, n_texts, size):
    r = random.Random(seed)
    text = lambda n: " ".join(r.choices(words, k=n))
    return decontaminate.Queries.of([(str(k), text(30)) for k in range(40)], 4), [text(size) for _ in range(n_texts)]


def test_a_shard_takes_few_numbers_a_word():
    queries, texts = made(1, [f"w{k}" for k in range(200)], 100, 4000)
    assert len(queries.array.order)
    tracemalloc.start()
    try:
        found = decontaminate.search_shard(texts, queries)
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    assert len(found) == 100 and all(f["longest"] for f in found)
    assert peak < 80 * 400_000, peak / 400_000


def test_slices_of_places_change_nothing(monkeypatch):
    queries, texts = made(2, list("abcdef"), 20, 300)
    whole = decontaminate.search_shard([*texts, "", None], queries)
    monkeypatch.setattr(decontaminate, "SLICE", 7)
    assert decontaminate.search_shard([*texts, "", None], queries) == whole


def test_shrink_runs(spark):
    shrink(spark)
