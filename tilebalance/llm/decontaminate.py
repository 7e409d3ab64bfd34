"""Benchmark decontamination by suffix arrays over the training text.

Training documents are gathered into shards of bounded word count (a longer
document is a shard of its own, never cut).  Each shard gets a word-level suffix
array, sorted to the depth of the longest benchmark item.  Every start of a whole
benchmark window is looked up in it by binary search, which gives the hits.  For
the longest verbatim match of each document, of whatever length, the suffixes of
the shard and those of the benchmark are merged: a suffix agrees longest with one
of its two neighbours, found by binary search as well.  Words that no benchmark
item has share one number below all others: a suffix that starts with one cannot
match and is left out of the array.

The benchmark is the stated query set.  It is dealt into blocks of about a given
size; the driver holds one block at a time and sends it to tasks, one pass over
the documents for each block.
"""

from __future__ import annotations

from array import array
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise, tidy

WINDOW, SHARD_WORDS, BLOCK_BYTES = 10, 1_000_000, 16 << 20
#: Places of a shard handled at a time where each takes many numbers.
SLICE = 1 << 16
_TABLE = bytes(c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else c + 32 if 65 <= c <= 90 else 32 for c in range(256))


def words_of(text: str | None) -> list[bytes]:
    """Runs of ASCII digits, letters (A-Z lower-cased) and all characters beyond ASCII."""
    return (text or "").encode().translate(_TABLE).split()


@dataclass
class Queries:
    """A block of benchmark items: word numbers from 1, all items in a row, each followed by a 0."""

    items: list[str]
    number: dict[bytes, int]
    flat: np.ndarray
    starts: np.ndarray
    lengths: np.ndarray
    window: int
    own: list = field(default_factory=list)

    def __getstate__(self):
        return self.__dict__ | {"own": []}

    @property
    def array(self) -> SuffixArray:
        """The suffix array of the items, made once in each worker."""
        if not self.own:
            self.own.append(SuffixArray(self.flat, len(self.number), int(self.lengths.max())))
        return self.own[0]

    @classmethod
    def of(cls, items: list[tuple[str, str | None]], window: int) -> Queries:
        words = [(i, w) for i, w in ((i, words_of(t)) for i, t in items) if w]
        number = {w: k + 1 for k, w in enumerate(sorted({x for _, w in words for x in w}))}
        lengths = np.array([len(w) for _, w in words], np.int64)
        flat = np.zeros(int((lengths + 1).sum()), np.int64)
        starts = np.concatenate([[0], np.cumsum(lengths + 1)])[:-1].astype(np.int64)
        for s, (_, w) in zip(starts, words):
            flat[s : s + len(w)] = [number[x] for x in w]
        return cls([i for i, _ in words], number, flat, starts, lengths, window)

    def windows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(place in flat, words, item) of every window."""
        count = np.maximum(1, self.lengths - self.window + 1)
        item = np.repeat(np.arange(len(count)), count)
        first = np.repeat(np.cumsum(count) - count, count)
        return self.starts[item] + np.arange(len(item)) - first, np.minimum(self.window, self.lengths)[item], item


class SuffixArray:
    """Suffixes of a word sequence (0: no benchmark word) in order of their first `depth` words."""

    def __init__(self, ids: np.ndarray, n_words: int, depth: int):
        self.bits = max(1, int(n_words).bit_length())
        self.per = max(1, 62 // self.bits)
        self.n = len(ids)
        key = np.zeros(self.n, np.int64)
        for k in range(self.per):
            key <<= self.bits
            key[: max(0, self.n - k)] |= ids[k:]
        self.ids, self.key = ids, key
        live = np.flatnonzero(ids).astype(np.int32 if self.n < 2**31 else np.int64)
        order = live[np.argsort(key[live], kind="stable")]
        del live
        # Ties are sorted further, a packed key at a time, until none is left or the depth is reached.
        done = self.per
        group = self._groups(key[order])
        while done < depth and len(order):
            tied = np.flatnonzero(np.bincount(group)[group] > 1)
            if not len(tied):
                break
            nxt = self.key_at(order[tied], done)
            again = np.lexsort((nxt, group[tied]))
            order[tied] = order[tied][again]
            change = np.zeros(len(order), bool)
            change[1:] = group[1:] != group[:-1]
            sorted_next, same = nxt[again], group[tied][again]
            change[tied[1:]] |= (sorted_next[1:] != sorted_next[:-1]) & (same[1:] == same[:-1])
            group = np.cumsum(change, dtype=np.int32)
            done += self.per
        self.order = order

    @staticmethod
    def _groups(keys: np.ndarray) -> np.ndarray:
        group = np.zeros(len(keys), np.int32)
        np.cumsum(keys[1:] != keys[:-1], dtype=np.int32, out=group[1:])
        return group

    def key_at(self, place: np.ndarray, ahead: int) -> np.ndarray:
        at = place + ahead
        return np.where(at < self.n, self.key[np.minimum(at, self.n - 1)], 0)

    def _bound(self, lo: np.ndarray, hi: np.ndarray, ahead: int, target: np.ndarray, right: bool) -> np.ndarray:
        """First position in [lo, hi) whose key, `ahead` words on, is >= target (> if right)."""
        lo, hi = lo.copy(), hi.copy()
        while (open_ := lo < hi).any():
            mid = (lo + hi) >> 1
            got = self.key_at(self.order[np.minimum(mid, len(self.order) - 1)], ahead)
            below = (got <= target) if right else (got < target)
            lo, hi = np.where(open_ & below, mid + 1, lo), np.where(open_ & ~below, mid, hi)
        return lo

    def search(self, flat: np.ndarray, at: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ranges of the array whose suffixes start with flat[at : at + length], one range for each."""
        lo, hi = np.zeros(len(at), np.int64), np.full(len(at), len(self.order), np.int64)
        for ahead in range(0, int(length.max(initial=0)), self.per):
            low, top = np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)
            for k in range(ahead, ahead + self.per):
                inside = k < length
                word = np.where(inside, flat[np.minimum(at + k, len(flat) - 1)], 0)
                low = (low << self.bits) | word
                top = (top << self.bits) | np.where(inside, word, (1 << self.bits) - 1)
            lo, hi = self._bound(lo, hi, ahead, low, False), self._bound(lo, hi, ahead, top, True)
        return lo, np.maximum(lo, hi)


    def words_of(self, keys: np.ndarray, k: int) -> np.ndarray:
        """Word k of packed keys."""
        return (keys >> (self.bits * (self.per - 1 - k))) & ((1 << self.bits) - 1)

    def agreement(self, mine: np.ndarray, other: np.ndarray) -> np.ndarray:
        """Leading words that packed keys share, up to the first 0."""
        out, alive = np.zeros(len(mine), np.int64), np.ones(len(mine), bool)
        for k in range(self.per):
            word = self.words_of(mine, k)
            alive &= (word == self.words_of(other, k)) & (word > 0)
            out += alive
        return out


def longest_runs(shard: SuffixArray, other: SuffixArray) -> np.ndarray:
    """For each place in the shard, how many words from there on occur in a row somewhere in the other array's text.  A slice of places at a time: each takes many numbers a place."""
    out, keys = np.zeros(shard.n, np.int32), other.key[other.order]
    if len(keys):
        for a in range(0, len(shard.order), SLICE):
            _runs_from(shard, other, keys, shard.order[a : a + SLICE], out)
    return out


def _runs_from(shard: SuffixArray, other: SuffixArray, keys: np.ndarray, place: np.ndarray, out: np.ndarray) -> None:
    mine = shard.key[place]
    lo, hi = np.searchsorted(keys, mine, "left"), np.searchsorted(keys, mine, "right")
    first, last = np.zeros(len(place), np.int64), np.full(len(place), len(keys), np.int64)
    ahead = 0
    while len(place):
        # Neighbours where the order would place the suffix, among those that agree so far.
        for near in (lo - 1, hi):
            inside = (near >= first) & (near < last)
            got = other.key_at(other.order[np.clip(near, 0, len(keys) - 1)], ahead)
            out[place[inside]] = np.maximum(out[place[inside]], ahead + shard.agreement(mine[inside], got[inside]))
        found = lo < hi
        out[place[found]] = ahead + shard.agreement(mine[found], mine[found])
        go = found & (out[place] == ahead + shard.per)
        place, first, last = place[go], lo[go], hi[go]
        ahead += shard.per
        mine = shard.key_at(place, ahead)
        lo, hi = other._bound(first, last, ahead, mine, False), other._bound(first, last, ahead, mine, True)


def search_shard(texts: list[str | None], queries: Queries) -> list[dict]:
    """For each text: n_words, spans (disjoint word ranges inside benchmark windows), items, and its longest verbatim match (words, item, where in both)."""
    get, rows, sizes = queries.number.get, array("i"), []
    for text in texts:
        words = words_of(text)
        rows.extend([get(w, 0) for w in words])
        rows.append(0)
        sizes.append(len(words))
    out = [{"n_words": n, "spans": [], "items": [], "longest": 0, "longest_item": None, "longest_at": None, "longest_from": None} for n in sizes]
    ids = np.array(rows, np.int32)
    del rows
    if not len(queries.items) or not ids.any():
        return out
    starts = np.concatenate([[0], np.cumsum(np.array(sizes, np.int64) + 1)])[:-1]
    shard = SuffixArray(ids, len(queries.number), int(queries.lengths.max()))
    _longest(shard, starts, queries, out)
    at, length, item = queries.windows()
    lo, hi = shard.search(queries.flat, at, length)
    count = hi - lo
    if not count.any():
        return out
    q = np.repeat(np.arange(len(at)), count)
    place = shard.order[np.repeat(lo - (np.cumsum(count) - count), count) + np.arange(len(q))]
    edge = np.bincount(place, minlength=len(ids) + 1)
    edge -= np.bincount(place + length[q], minlength=len(ids) + 1)
    hit = np.concatenate([np.zeros(1, np.int8), (np.cumsum(edge, out=edge)[: len(ids)] > 0).astype(np.int8), np.zeros(1, np.int8)])
    step = np.diff(hit)
    begin, end = np.flatnonzero(step > 0), np.flatnonzero(step < 0)
    for a, b in zip(begin, end):
        d = int(np.searchsorted(starts, a, side="right")) - 1
        out[d]["spans"].append((int(a - starts[d]), int(b - starts[d])))
    doc = np.searchsorted(starts, place, side="right") - 1
    for d, i in np.unique(np.stack([doc, item[q]]), axis=1).T:
        out[d]["items"].append(queries.items[i])
    return out


def _longest(shard: SuffixArray, starts: np.ndarray, queries: Queries, out: list[dict]) -> None:
    """The longest match of each document: of equal ones the first in the document, then the first item and place."""
    run = longest_runs(shard, queries.array)
    best = np.maximum.reduceat(run, starts)
    found = []
    for a in range(0, len(run), SLICE):
        mine = run[a : a + SLICE]
        of = np.searchsorted(starts, np.arange(a, a + len(mine)), side="right") - 1
        top = np.flatnonzero((mine > 0) & (mine == best[of]))
        found.append((of[top], a + top))
    docs, first = np.unique(np.concatenate([d for d, _ in found]), return_index=True)
    place = np.concatenate([p for _, p in found])[first]
    lo, hi = queries.array.search(shard.ids, place, run[place])
    for d, p, a, b in zip(docs.tolist(), place.tolist(), lo.tolist(), hi.tolist()):
        begin = int(queries.array.order[a:b].min())
        item = int(np.searchsorted(queries.starts, begin, side="right")) - 1
        out[d] |= {"longest": int(run[p]), "longest_item": queries.items[item], "longest_at": int(p - starts[d]), "longest_from": int(begin - queries.starts[item])}


_SPAN = pa.list_(pa.struct([("s", pa.int64()), ("e", pa.int64())]))
_FIELDS = [("n_words", pa.int64(), "bigint"), ("spans", _SPAN, "array<struct<s:bigint,e:bigint>>"), ("items", pa.list_(pa.string()), "array<string>"), ("longest", pa.int64(), "bigint"), ("longest_item", pa.string(), "string"), ("longest_at", pa.int64(), "bigint"), ("longest_from", pa.int64(), "bigint")]
_KIND = "found struct<" + ",".join(f"{n}:{k}" for n, _, k in _FIELDS) + ">"


def dealt(benchmark: DataFrame, block_bytes: int) -> tuple[DataFrame, int]:
    """The benchmark's items (i, text) with a block number, and how many blocks of about block_bytes of text there are."""
    rows = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("string").alias("i"), F.col("text").cast("string").alias("text")).distinct()
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = max(1, -(-size // block_bytes))
    return rows.withColumn("block", F.pmod(F.xxhash64("i", "text"), F.lit(n))), n


def block(items: DataFrame, k: int, window: int) -> Queries:
    """One block, which alone comes to the driver."""
    return Queries.of(sorted((r.i, r.text) for r in items.where(F.col("block") == k).select("i", "text").collect()), window)


def _pass(queries: Queries, shard_words: int):
    kind = pa.struct([(n, t) for n, t, _ in _FIELDS])

    def run(batches):
        def flush():
            ids, texts = zip(*held)
            rows = pa.array([f | {"spans": [{"s": s, "e": e} for s, e in f["spans"]]} for f in search_shard(list(texts), queries)], kind)
            return pa.RecordBatch.from_arrays([pa.array(ids, key), rows], names=["doc_id", "found"])

        held, size, key = [], 0, pa.int64()
        for batch in batches:
            key = batch.column(0).type
            for k in range(batch.num_rows):
                text = batch.column(1)[k].as_py()
                held.append((batch.column(0)[k].as_py(), text))
                size += len(text or "") // 5 + 1
                if size >= shard_words:
                    yield flush()
                    held, size = [], 0
        if held:
            yield flush()

    return tidy(run)


def find(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", shard_words: int = SHARD_WORDS, block_bytes: int = BLOCK_BYTES, id_type: str = "bigint") -> DataFrame:
    """One row per input row: doc_id, n_words, n_hit, spans, items (ids as sorted strings), longest, longest_item, longest_at, longest_from.

    A window is `window` consecutive words of an item; an item of fewer, but at
    least one, is one window.  Null and empty texts have no words; a benchmark
    row with a null id or text, or without words, is no item; rows that repeat
    an id add their windows to that item.  `longest` counts matches of any
    length, a word at least; of equally long matches the first in the document
    counts, then the first item (ids as strings).  Repeated documents are each
    reported; only the named columns are read; empty tables give no rows or no
    hits.  With several blocks each one's findings are written and then joined
    by row.
    """
    df = docs.select(F.col(id_col).cast(id_type).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    items, n = dealt(benchmark, block_bytes)
    if n == 1:
        every = df.mapInArrow(_pass(block(items, 0, window), shard_words), f"doc_id {id_type}, {_KIND}").select("doc_id", F.array("found").alias("found"))
    else:
        items = materialise(items, "items")
        rows = materialise(df.withColumn("_row", F.monotonically_increasing_id()), "rows")
        own = None
        for k in range(n):
            found = materialise(rows.select(F.col("_row").alias("doc_id"), "text").mapInArrow(_pass(block(items, k, window), shard_words), f"doc_id bigint, {_KIND}"), "found")
            own = found if own is None else own.unionByName(found)
        every = rows.select("doc_id", "_row").join(own.groupBy(F.col("doc_id").alias("_row")).agg(F.collect_list("found").alias("found")), "_row").select("doc_id", "found")  # a row has one finding a block
    spans = F.flatten(F.col("found.spans"))
    if n > 1:
        spans = F.aggregate(
            F.array_sort(spans),
            F.array().cast("array<struct<s:bigint,e:bigint>>"),
            lambda acc, x: F.when((F.size(acc) > 0) & (F.element_at(acc, -1)["e"] >= x["s"]), F.concat(F.slice(acc, 1, F.greatest(F.size(acc) - 1, F.lit(0))), F.array(F.struct(F.element_at(acc, -1)["s"].alias("s"), F.greatest(F.element_at(acc, -1)["e"], x["e"]).alias("e"))))).otherwise(F.concat(acc, F.array(x))),
        )
    first = F.array_min(F.transform("found", lambda x: F.struct((-x["longest"]).alias("n"), x["longest_at"].alias("p"), x["longest_item"].alias("i"), x["longest_from"].alias("f"))))
    return (
        every.select("doc_id", F.col("found")[0]["n_words"].alias("n_words"), spans.alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.col("found.items")))).alias("items"), first.alias("b"))
        .select("doc_id", "n_words", F.aggregate("spans", F.lit(0).cast("bigint"), lambda acc, x: acc + x["e"] - x["s"]).alias("n_hit"), "spans", "items", (-F.col("b.n")).alias("longest"), F.col("b.i").alias("longest_item"), F.col("b.p").alias("longest_at"), F.col("b.f").alias("longest_from"))
    )


def report(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The digest of find(): doc_id, n_words, n_hit, n_items, items_sha256, contaminated, longest."""
    return find(docs, benchmark, **options).select("doc_id", "n_words", "n_hit", F.size("items").cast("bigint").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"), "longest")
