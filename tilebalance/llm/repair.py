"""Token-id shards compressed by Re-Pair grammars.

A shard holds consecutive documents (about SHARD_TOKENS ids; a longer document
is a shard of its own).  Frequent pairs of neighbouring symbols are replaced by
new symbols, round after round, until no pair is frequent; pairs never reach
over the end of a document.  The file keeps the rules, the length of each
symbol's expansion and where each document's symbols begin, so any stretch of
any document is decoded without the rest.

File format, little-endian: the 4 bytes RPG1; uint32 base (ids below it are
plain), docs, rules, rounds, symbols; then int64 doc_id[docs], uint8
null_id[docs], int64 start[docs] (ids before it in the writer's range), uint32
ids[docs], uint32 begin[docs + 1] (first symbol), uint32 round_end[rounds],
uint32 left[rules], uint32 right[rules], uint32 expanded[rules], uint32
symbol[symbols].
"""

from __future__ import annotations

import codecs
import os
import re
import struct
import zlib
from array import array
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import fresh_path, kept, slices, tidy

MAGIC = b"RPG1"
SHARD_TOKENS, MIN_USES, BUCKET_BITS = 1 << 20, 4, 18
#: Bytes of text whose runs are looked up at a time: the more, the more of them are the same.
ENCODE_BYTES = 4_000_000
END_ID = 2
_SPACE = re.compile("[\t-\r \x85\xa0  -     　]+")
_BEYOND = re.compile("[^\x00-į]")
_ALNUM = np.array([chr(c).isalnum() for c in range(0x130)] + [False])


class Encoder:
    """Whole texts to ids by the tokenizers library.

    Only for vocabularies that drop white space: no token spans it, so each
    run of other characters is encoded once by the library and remembered (up
    to a limit).  Texts in the Latin ranges are lower-cased before, as such a
    vocabulary's normaliser does.
    """

    MARK = "|"

    def __init__(self, path: str, limit: int = 1_200_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer, self.limit = Tokenizer.from_file(path), limit
        self.wide = self.tokenizer.get_vocab_size() > 1 << 16
        self.kind = np.dtype("<u4" if self.wide else "<u2")
        self.known: dict[str, bytes] = {}
        self.mark = (self.ids(self.MARK) or [-1])[0]
        if len(self.ids(self.MARK)) != 1 or len(self.ids("Ab\tcD  e")) != len(self.ids("ab cd e")) or self.ids("\n "):
            raise ValueError("the vocabulary keeps white space or case")
        shown = sorted({*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)})
        self.model = self.tokenizer.model
        letters = dict(zip(sorted(set(range(256)) - set(shown)), range(256, 512)))
        self.letters = "".join(chr(letters.get(b, b)) for b in range(256))
        words = ["cloudberry", "stra\xdfe", "na\xefve", "\xe0\xf1\xfe", "z"]
        self.direct = self.tokenizer.pre_tokenizer is not None and all(self.word(w) == np.array(self.ids(w), self.kind).tobytes() for w in words)
        apart = lambda t: all(self.ids(w + t) == self.ids(w) + self.ids(t) for w in [*words, "it's", "a1"])
        tails = [t for t in ".,;:!?#*&%$" if apart(t) and apart(t * 3)]
        self.tails = "".join(tails if all(apart(t + u) for t in tails for u in tails) else [])

    @classmethod
    def at(cls, path: str) -> "Encoder":
        models = kept("repair")
        if path not in models:
            models[path] = cls(path)
        return models[path]

    def ids(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """The ids of each text as packed little-endian numbers.  Runs are looked up once for all texts, cut into core and marks before."""
        if len(self.known) > self.limit:
            self.known.clear()
        clean, odd = [], False
        for text in texts:
            text = text or ""
            wide = self.beyond(text)
            if not wide and "<|" not in text:  # special tokens keep their case
                text = text.lower()
            if not text.isascii():
                text = _SPACE.sub(" ", text) if wide else text.replace("\x85", " ").replace("\xa0", " ")
            clean.append(text)
            odd |= wide
        runs = pc.ascii_split_whitespace(pa.array(clean, pa.large_string()))
        coded = runs.values.dictionary_encode()
        words = coded.dictionary
        parts = pa.concat_arrays(self.cut(words, odd)).dictionary_encode()
        names, known = parts.dictionary.to_numpy(zero_copy_only=False).tolist(), self.known
        found = list(map(known.get, names))
        if new := [i for i, held in enumerate(found) if held is None]:
            self.learn([names[i] for i in new])
            for i in new:
                found[i] = known[names[i]]
        ids = pa.array(found, pa.large_binary()).take(parts.indices)
        ids = pc.binary_join_element_wise(ids[: len(words)], ids[len(words) :], pa.scalar(b"", pa.large_binary())).take(coded.indices)
        ends = np.frombuffer(ids.buffers()[1], np.int64)[runs.offsets.to_numpy()].tolist() if len(ids) else [0] * (len(texts) + 1)
        data = memoryview(ids.buffers()[2] or b"")
        return [data[a:b].tobytes() for a, b in zip(ends, ends[1:])]

    def cut(self, words: pa.LargeStringArray, odd: bool) -> list[pa.Array]:
        """Core and marks of each run.  Marks after a letter or digit are cut off it; other runs, and those beyond the Latin ranges (odd: there may be some), stay whole."""
        core = pc.ascii_rtrim(words, characters=self.tails)
        begin, data = np.frombuffer(words.buffers()[1], np.int64)[: len(words) + 1], np.frombuffer(words.buffers()[2] or b" ", np.uint8)
        full, held = np.diff(begin), pc.binary_length(core).to_numpy()
        end = begin[:-1] + held
        last, lead = data[np.maximum(end - 1, 0)].astype(np.int32), data[np.maximum(end - 2, 0)].astype(np.int32)
        code = np.where(last < 0x80, last, np.where((lead >= 0xC2) & (lead <= 0xC4) & (held > 1), (lead & 0x1F) << 6 | last & 0x3F, 0))
        apart = (held < full) & (held > 0) & _ALNUM[np.minimum(code, len(_ALNUM) - 1)]
        if odd:
            apart &= ~pc.match_substring_regex(words, _BEYOND.pattern).to_numpy(zero_copy_only=False)
        n = np.where(apart, full - held, 0)
        after = np.concatenate([[0], np.cumsum(n)])
        marks = data[np.repeat(end - after[:-1], n) + np.arange(after[-1])]
        tail = pa.LargeStringArray.from_buffers(len(words), pa.py_buffer(after), pa.py_buffer(marks))
        return [pc.if_else(pa.array(apart), core, words), tail]

    @staticmethod
    def beyond(text: str) -> bool:
        """Whether a text has characters beyond the Latin ranges."""
        if text.isascii():
            return False
        try:
            text.encode("latin-1")
            return False
        except UnicodeEncodeError:
            return bool(_BEYOND.search(text))

    def word(self, word: str) -> bytes:
        """Ids of lower-case Latin letters by the library's model alone: nothing is to be normalised or cut there."""
        if not word.isascii():
            word = codecs.charmap_decode(word.encode(), "strict", self.letters)[0]
        return array(self.kind.char, [t.id for t in self.model.tokenize(word)]).tobytes()

    def learn(self, words: list[str]) -> None:
        """Encode new runs of characters: plain words one by one, others many to a call."""
        known, beyond, word, direct, runs = self.known, self.beyond, self.word, self.direct, []
        for w in words:
            if direct and w.isalpha() and w.islower() and (w.isascii() or not beyond(w)):
                known[w] = word(w)
            else:
                runs.append(w)
        self.learn_runs(runs)

    def learn_runs(self, words: list[str]) -> None:
        """Encode any runs, many to a call: a mark that stands alone between them is one id, at which the result is cut."""
        kind, known = self.kind, self.known
        plain = [w for w in words if self.MARK not in w and not _BEYOND.search(w)]
        joint = f" {self.MARK} "
        for a in range(0, len(plain), 500):
            part = plain[a : a + 500]
            ids = np.array(self.tokenizer.encode_batch_fast([joint.join(part)], add_special_tokens=False)[0].ids, kind)
            cuts = [-1, *np.flatnonzero(ids == self.mark).tolist(), len(ids)]
            data, size = ids.tobytes(), kind.itemsize
            if len(cuts) != len(part) + 1:
                raise RuntimeError("a mark was not kept apart")
            for w, i, j in zip(part, cuts, cuts[1:]):
                known[w] = data[(i + 1) * size : j * size]
        other = [w for w in words if self.MARK in w or _BEYOND.search(w)]
        for w, e in zip(other, self.tokenizer.encode_batch_fast(other, add_special_tokens=False) if other else []):
            known[w] = np.array(e.ids, kind).tobytes()


def compress(ids: np.ndarray, last: np.ndarray, base: int, min_uses: int = MIN_USES, bits: int = BUCKET_BITS) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[int]]:
    """(symbols, rules as an n x 2 array, last marks, ends of rounds).  last marks each document's last id.

    A round counts pairs in hashed buckets, each for one representative pair,
    takes those above a level that falls from an eighth of the highest count to
    min_uses by eighths, and replaces, where chosen pairs overlap, the commoner
    (of equals, that of the higher bucket) one; in a run of one symbol every
    second place is taken.  Pairs that lost a bucket come in a later round under
    another hash.  The count of a pair of old symbols never grows, so places
    whose whole bucket is rare are not looked at again until a neighbour changes.

    A round that replaces nothing at the lowest level is followed by one that
    counts every pair exactly, without overlaps.  There the first in rank gets
    all its uses, so such a round replaces something or no pair is frequent,
    which alone ends the loop.
    """
    seq, live, stop = ids.astype(np.int32), ~last, np.flatnonzero(last)  # stop: places of documents' last symbols
    rules, ends, fresh, exact, level, k = [], [], base, False, 1 << 40, 0
    while True:
        at = np.flatnonzero(live)
        if not len(at):
            break
        pair = (seq.take(at).astype(np.int64) << 32) | seq.take(at + 1)
        if exact:
            _, bucket = np.unique(pair, return_inverse=True)
            n_buckets = int(bucket.max()) + 1
            use = _places(at, bucket)
            common = (np.bincount(bucket[use], minlength=n_buckets) >= min_uses).take(bucket)
        else:
            width = min(bits, max(8, len(at).bit_length()))
            n_buckets = 1 << width
            odd = np.uint64((0x9E3779B97F4A7C15 * (2 * k + 1)) & ((1 << 64) - 1) | 1)
            bucket = ((pair.view(np.uint64) * odd) >> np.uint64(64 - width)).view(np.int64)  # numpy's own kind of index: others are copied at each use
            common = (np.bincount(bucket, minlength=n_buckets) >= min_uses).take(bucket)
        k += 1
        live[at] = common
        stay = np.flatnonzero(common)
        at, pair, bucket = at.take(stay), pair.take(stay), bucket.take(stay)
        if not len(at):
            break
        slots = np.zeros(n_buckets, np.int64)
        slots[bucket] = pair
        own = slots.take(bucket) == pair
        count = np.bincount(bucket[own], minlength=n_buckets)
        level = min(level, int(count.max())) >> 3
        least = max(min_uses, level)
        picked = np.flatnonzero(own & (count >= least).take(bucket))
        place, home = at[picked], bucket[picked]
        rank = count[home] * n_buckets + home
        take = _places(place, home)
        beside = place[1:] == place[:-1] + 1
        take[1:] &= ~beside | (rank[1:] >= rank[:-1])
        take[:-1] &= ~beside | (rank[:-1] >= rank[1:])
        uses = np.bincount(home[take], minlength=n_buckets)
        kept = np.flatnonzero(uses >= min_uses)
        if not len(kept):
            exact = least == min_uses
            continue
        exact = False
        number = np.full(n_buckets, -1, np.int32)
        number[kept] = fresh + np.arange(len(kept), dtype=np.int32)
        new = number[home]
        take &= new >= 0
        chosen = place[take]
        used = slots[kept]
        rules.append(np.stack([used >> 32, used & 0xFFFFFFFF], 1))
        fresh += len(kept)
        ends.append(fresh - base)
        seq[chosen] = new[take]
        live[chosen] = True
        live[np.maximum(chosen - 1, 0)] = True
        stay = np.ones(len(seq), bool)
        stay[chosen + 1] = False
        stay = np.flatnonzero(stay)
        seq, live = seq.take(stay), live.take(stay)
        stop = stop - np.searchsorted(chosen + 1, stop, side="right")
        live[stop] = False
    last = np.zeros(len(seq), bool)
    last[stop] = True
    return seq, np.concatenate(rules) if rules else np.zeros((0, 2), np.int64), last, ends


def _places(place: np.ndarray, home: np.ndarray) -> np.ndarray:
    """Of each stretch of neighbouring places of one pair, that is a run of one symbol, every second place from the left."""
    starts = np.ones(len(place), bool)
    starts[1:] = (place[1:] != place[:-1] + 1) | (home[1:] != home[:-1])
    index = np.arange(len(place))
    return (index - np.maximum.accumulate(np.where(starts, index, 0))) % 2 == 0


def pack(doc_ids: list[int | None], starts: list[int], docs: list[np.ndarray], base: int, **options) -> bytes:
    """One shard file.  Every document has at least one id."""
    sizes = np.array([len(d) for d in docs], np.int64)
    flat = np.concatenate(docs) if docs else np.zeros(0, np.int64)
    last = np.zeros(len(flat), bool)
    last[np.cumsum(sizes) - 1] = True
    seq, rules, marks, ends = compress(flat, last, base, **options)
    begin = np.concatenate([[0], np.flatnonzero(marks) + 1])
    long = np.ones(base + len(rules), np.int64)
    a = 0
    for b in ends:
        long[base + a : base + b] = long[rules[a:b, 0]] + long[rules[a:b, 1]]
        a = b
    put = lambda x, kind: np.asarray(x).astype(kind).tobytes()
    return b"".join(
        [MAGIC, struct.pack("<5I", base, len(docs), len(rules), len(ends), len(seq)), put([d or 0 for d in doc_ids], "<i8"), put([d is None for d in doc_ids], "u1"), put(starts, "<i8"), put(sizes, "<u4"),
         put(begin, "<u4"), put(ends, "<u4"), put(rules[:, 0], "<u4"), put(rules[:, 1], "<u4"), put(long[base:], "<u4"), put(seq, "<u4")]
    )


@dataclass
class Shard:
    """A shard file opened for reading."""

    blob: bytes

    def __post_init__(self):
        if self.blob[:4] != MAGIC:
            raise ValueError("not a grammar shard")
        self.base, docs, rules, rounds, symbols = struct.unpack_from("<5I", self.blob, 4)
        at = 24

        def take(n: int, kind: str) -> np.ndarray:
            nonlocal at
            out = np.frombuffer(self.blob, kind, n, at)
            at += out.nbytes
            return out

        self.doc_id, self.null_id, self.start, self.sizes = take(docs, "<i8"), take(docs, "u1"), take(docs, "<i8"), take(docs, "<u4")
        self.begin, self.ends = take(docs + 1, "<u4"), take(rounds, "<u4")
        self.left, self.right, self.expanded, self.symbols = take(rules, "<u4"), take(rules, "<u4"), take(rules, "<u4"), take(symbols, "<u4")

    def all_ids(self) -> np.ndarray:
        """Every id of the shard: rules are expanded round by round, then the symbols at once."""
        base, rules = self.base, len(self.left)
        long = np.concatenate([np.ones(base, np.int64), self.expanded.astype(np.int64)])
        begin = np.concatenate([np.arange(base), base + np.concatenate([[0], np.cumsum(self.expanded.astype(np.int64))])[:-1]]) if rules else np.arange(base)
        flat = np.zeros(base + int(self.expanded.sum()), np.uint32)
        flat[:base] = np.arange(base)

        def expand(symbols: np.ndarray) -> np.ndarray:
            n = long[symbols]
            return flat[np.repeat(begin[symbols] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))]

        a = 0
        for b in self.ends.tolist():
            out = expand(np.stack([self.left[a:b], self.right[a:b]], 1).ravel())
            flat[begin[base + a] : begin[base + a] + len(out)] = out
            a = b
        return expand(self.symbols)

    def ids(self, doc: int, first: int = 0, stop: int | None = None) -> list[int]:
        """Ids first to stop of one document; only the symbols that hold them are expanded."""
        stop = int(self.sizes[doc]) if stop is None else min(stop, int(self.sizes[doc]))
        own = self.symbols[self.begin[doc] : self.begin[doc + 1]].astype(np.int64)
        rule = own - self.base
        long = np.where(rule < 0, 1, self.expanded[np.maximum(rule, 0)] if len(self.expanded) else 1).astype(np.int64)
        after = np.cumsum(long)
        out: list[int] = []
        if first >= stop:
            return out
        k = int(np.searchsorted(after, first, side="right"))
        place = int(after[k] - long[k])
        while place < stop:
            todo = [int(own[k])]
            while todo and place < stop:
                s = todo.pop()
                n = 1 if s < self.base else int(self.expanded[s - self.base])
                if place + n <= first:
                    place += n
                elif s < self.base:
                    out.append(s)
                    place += 1
                else:
                    todo += [int(self.right[s - self.base]), int(self.left[s - self.base])]
            k += 1
        return out


def encode(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids): packed ids of each whole text, null as empty, without special or end ids."""

    def run(batches):
        own = Encoder.at(vocabulary)
        for batch in batches:
            for a, b in slices(batch.column(1), ENCODE_BYTES):
                part = batch.slice(a, b - a)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(own.encode(part.column(1).to_pylist()), pa.binary())], names=["doc_id", "ids"])

    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id bigint, ids binary")


def write(docs: DataFrame, path: str, vocabulary: str, end_id: int = END_ID, shard_tokens: int = SHARD_TOKENS, id_col: str = "doc_id", text_col: str = "text", parts: int | None = None) -> None:
    """Encode whole texts, append end_id to each, and write shard files in ascending doc_id order (null ids first, equal ids by their ids' bytes).

    Ranges of doc_id are cut at approximate quantiles of the id column, which
    are read alone; rows of one id stay together.  Each row of the table at
    `path` is a file: part, shard (in its part), n_docs, n_tokens, blob.
    """
    spark = docs.sparkSession
    parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    cuts = docs.select(F.percentile_approx(F.col(id_col).cast("bigint"), [k / parts for k in range(1, parts)], 100 * parts).alias("c")).first().c if parts > 1 else None
    cuts = sorted(set(cuts or []))
    part = F.coalesce(F.size(F.filter(F.lit(cuts), lambda c: c < F.col("doc_id"))), F.lit(0)) if cuts else F.lit(0)
    wide = Encoder.at(vocabulary).wide
    base = Encoder.at(vocabulary).tokenizer.get_vocab_size(True)
    base = max(base, end_id + 1)

    def run(batches):
        held: list[tuple[int | None, int, np.ndarray]] = []
        size = start = shard = number = 0
        end = np.array([end_id], np.int32)

        def flush():
            ids, starts, arrays = zip(*held)
            return pa.RecordBatch.from_arrays(
                [pa.array([number], pa.int32()), pa.array([shard], pa.int32()), pa.array([len(ids)], pa.int64()), pa.array([size], pa.int64()), pa.array([pack(list(ids), list(starts), list(arrays), base)], pa.binary())],
                names=["part", "shard", "n_docs", "n_tokens", "blob"],
            )

        for batch in batches:
            for number, doc_id, packed in zip(*[c.to_pylist() for c in batch.columns]):
                own = np.append(np.frombuffer(packed, "<u4" if wide else "<u2"), end)
                if held and size + len(own) > shard_tokens:
                    yield flush()
                    held, size, shard = [], 0, shard + 1
                held.append((doc_id, start, own))
                size += len(own)
                start += len(own)
        if held:
            yield flush()

    ordered = encode(docs, vocabulary, id_col, text_col).withColumn("part", part.cast("int")).select("part", "doc_id", "ids")
    placed = ordered.repartitionById(len(cuts) + 1, F.col("part")).sortWithinPartitions("doc_id", "ids")
    placed.mapInArrow(run, "part int, shard int, n_docs bigint, n_tokens bigint, blob binary").write.option("compression", "zstd").parquet(path)


def read(spark: SparkSession, path: str, ids: bool = False) -> DataFrame:
    """Per document of the files: doc_id, start (ids of all documents before), n_tokens, ids_crc32, and its ids if asked for."""
    files = spark.read.schema("part int, shard int, n_docs bigint, n_tokens bigint, blob binary").parquet(path)
    sums = files.groupBy("part").agg(F.sum("n_tokens").alias("n"))  # as many rows as ranges were written
    before = sums.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    kind = "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint" + ", ids array<bigint>" * ids

    def run(batches):
        for batch in batches:
            for before, blob in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                shard = Shard(blob)
                flat, ends = shard.all_ids(), np.cumsum(shard.sizes.astype(np.int64))
                docs = [flat[b - n : b] for b, n in zip(ends.tolist(), shard.sizes.tolist())]
                cols = [
                    pa.array([None if z else int(d) for d, z in zip(shard.doc_id, shard.null_id)], pa.int64()), pa.array(shard.start + before), pa.array(shard.sizes.astype(np.int64)),
                    pa.array([zlib.crc32(d.astype("<u4").tobytes()) for d in docs], pa.int64()),
                ]
                if ids:
                    cols.append(pa.array([d.tolist() for d in docs], pa.list_(pa.int64())))
                yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "start", "n_tokens", "ids_crc32", "ids"][: len(cols)])

    return files.select("part", "blob").join(F.broadcast(before), "part").select("before", "blob").mapInArrow(run, kind)


def round_trip(docs: DataFrame, vocabulary: str, **options) -> DataFrame:
    """Write to a fresh folder in the shared directory and read the files back.

    Null and empty texts hold the end id alone; repeated rows are repeated;
    columns other than the id and the text are not read; an empty table gives
    no rows.
    """
    path = fresh_path(docs.sparkSession, "grammar")
    write(docs, path, vocabulary, **options)
    return read(docs.sparkSession, path)
