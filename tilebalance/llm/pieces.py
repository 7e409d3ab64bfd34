"""SentencePiece encoding and decoding with a max-plus scan for giant documents.

The best segmentation of a text into pieces maximises a sum of scores, a walk in
the max-plus algebra.  A giant document is cut into chunks anywhere.  Its state
at a cut is how far back the last piece boundary lies (less than the longest
piece), and a chunk acts on states as a max-plus matrix.  Matrices are combined
associatively into the scores of every state at every cut; then each chunk is
traced back by itself for every state it may end in, and the documents' paths
are joined from those.

Where no piece can span two neighbouring characters every path has a boundary;
the stretches between such places (words, mostly) are solved once and remembered.

The vocabulary's pieces and scores are read from the model file.  A model whose
file says it is of the merge kind is treated as a unigram lattice over the same
scores: segmentations can differ from the merge procedure's, decoding does not.
"""

from __future__ import annotations

import hashlib
import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import kept, materialise, slices, tidy

CHUNK = 16_384
KNOWN_BYTES = 48 << 20  # of remembered stretches in a worker
SLOT_BITS = 18  # of a table of pieces
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = range(1, 7)
SPACE = "▁"
NONE = -np.inf


def _fields(data: bytes) -> Iterator[tuple[int, int, bytes | int]]:
    """(number, place of the value, value) of the fields of a protocol buffer message."""
    at = 0

    def varint() -> int:
        nonlocal at
        out = shift = 0
        while True:
            b = data[at]
            at += 1
            out |= (b & 127) << shift
            shift += 7
            if b < 128:
                return out

    while at < len(data):
        tag = varint()
        kind, place = tag & 7, at
        if kind == 0:
            value: bytes | int = varint()
        elif kind == 2:
            n = varint()
            place = at
            value = data[at : at + n]
            at += n
        else:
            n = 8 if kind == 1 else 4
            value = data[at : at + n]
            at += n
        yield tag >> 3, place, value


class Pieces:
    """A vocabulary as a lattice of scored pieces."""

    def __init__(self, path: str, limit: int = KNOWN_BYTES):
        with open(path, "rb") as f:
            data = f.read()
        self.pieces: list[tuple[str, float, int]] = []
        prefix, collapse, escape = True, True, True
        for number, _, value in _fields(data):
            if number == 1:
                own = {n: v for n, _, v in _fields(value)}
                self.pieces.append((own[1].decode(), struct.unpack("<f", own[2])[0] if 2 in own else 0.0, own.get(3, NORMAL)))
            elif number == 3:
                own = {n: v for n, _, v in _fields(value)}
                if own.get(2):
                    raise ValueError("normalisation tables are not supported")
                prefix, collapse, escape = bool(own.get(3, 1)), bool(own.get(4, 1)), bool(own.get(5, 1))
        if collapse or not escape:
            raise ValueError("only models that keep every space, escaped, decode exactly")
        self.prefix = prefix
        scores = [s for _, s, k in self.pieces if k in (NORMAL, USER, UNUSED)]
        low, high = min(scores), max(scores)
        self.score: dict[str, float] = {}
        self.id: dict[str, int] = {}
        self.byte = {int(p[3:5], 16): i for i, (p, _, k) in enumerate(self.pieces) if k == BYTE}
        for i, (p, s, k) in enumerate(self.pieces):
            if k in (NORMAL, USER):
                self.score[p] = s if k == NORMAL else len(p) * high - 0.1
                self.id[p] = i
        self.raw = [bytes([int(p[3:5], 16)]) if k == BYTE else b"" if k == CONTROL else p.encode() for p, _, k in self.pieces]
        if len(self.byte) != 256:
            raise ValueError("only models with byte fallback decode exactly")
        self.unknown = low - 10.0
        self.longest = max(map(len, self.score))
        if any(b == SPACE != a for p in self.score for a, b in zip(p, p[1:])):
            raise ValueError("pieces that hold a space after another character are not supported")
        inner = {c for p in self.score if len(p) > 1 for c in p} - {SPACE}
        own = "".join(map(re.escape, sorted(inner)))
        self.units = re.compile(f"{SPACE}*[{own}]+|{SPACE}+|.", re.S)
        self.alone = lambda c: c != SPACE and c not in inner
        self.known: dict[str, bytes] = {}
        self.limit, self.held = limit, 0
        self.tables: list[tuple[int, np.ndarray, np.ndarray]] = []

    @classmethod
    def at(cls, path: str) -> "Pieces":
        models = kept("pieces")
        if path not in models:
            models[path] = cls(path)
        return models[path]

    def escaped(self, text: str) -> str:
        return (SPACE + text if self.prefix and text else text).replace(" ", SPACE)

    def forced(self, a: str, b: str) -> bool:
        """Whether every path has a boundary between neighbouring characters a and b."""
        return self.alone(a) or self.alone(b) or (b == SPACE != a)

    def forward(self, text: str, init: dict[int, float], least_end: int) -> tuple[list[float], list[int]]:
        """Best score at each place and the start of the piece that ends there (-1: none).  Paths begin at the places of init; their first pieces end at least_end or later.  Of equal starts the earliest wins."""
        n, get, unknown, longest = len(text), self.score.get, self.unknown, self.longest
        best, back = [NONE] * (n + 1), [-1] * (n + 1)
        for at, s in init.items():
            best[at] = s
        for end in range(least_end, n + 1):
            top, start = best[end] if end in init else NONE, -1
            for a in range(max(0, end - longest), end):
                if best[a] == NONE:
                    continue
                s = get(text[a:end])
                if s is None:
                    if a != end - 1:
                        continue
                    s = unknown
                if best[a] + s > top:
                    top, start = best[a] + s, a
            best[end], back[end] = top, start
        return best, back

    def ids_of(self, piece: str) -> list[int]:
        found = self.id.get(piece)
        return [found] if found is not None else [self.byte[b] for b in piece.encode()]

    def path(self, text: str, back: list[int], end: int) -> tuple[list[int], int]:
        """(boundaries from the first to end, where the path begins)."""
        cuts = [end]
        while back[cuts[-1]] >= 0:
            cuts.append(back[cuts[-1]])
        return cuts[::-1], cuts[-1]

    def ids_on(self, text: str, cuts: list[int]) -> bytes:
        return np.array([i for a, b in zip(cuts, cuts[1:]) for i in self.ids_of(text[a:b])], "<u4").tobytes()

    def unit(self, text: str) -> bytes:
        """Ids of a stretch between two forced boundaries."""
        found = self.known.get(text)
        if found is None:
            _, back = self.forward(text, {0: 0.0}, 1)
            found = self.remember(text, self.ids_on(text, self.path(text, back, len(text))[0]))
        return found

    def remember(self, text: str, ids: bytes) -> bytes:
        self.known[text] = ids
        self.held += 200 + 2 * len(text) + len(ids)  # two objects and their place in the table
        return ids

    def room(self) -> None:
        """Forget all stretches once they hold more than the limit; called between slices only."""
        if self.held > self.limit:
            self.known.clear()
            self.held = 0

    def learn(self, units: set[str]) -> None:
        """Solve many stretches at once: those of one length go through the recurrence of forward() side by side."""
        by: dict[int, list[str]] = {}
        for u in units:
            by.setdefault(len(u), []).append(u)
        for n, own in by.items():
            if n > 48 or len(own) < 48:
                for u in own:
                    self.unit(u)
                continue
            for a in range(0, len(own), 20_000):
                self._solve(n, own[a : a + 20_000])

    def _table(self) -> list[tuple[int, np.ndarray, np.ndarray]]:
        """Pieces by a polynomial hash of their characters: (multiplier, hash in each slot, score in each slot), a second table for those whose slot was taken."""
        if not self.tables:
            base = np.array([self._hash(p) for p in self.score], np.uint64)
            scores = np.array(list(self.score.values()))
            left, odd = np.arange(len(base)), 0x9E3779B97F4A7C15
            while len(left):
                slot = ((base[left] * np.uint64(odd)) >> np.uint64(64 - SLOT_BITS)).astype(np.int64)
                _, first = np.unique(slot, return_index=True)
                hashes, values = np.zeros(1 << SLOT_BITS, np.uint64), np.full(1 << SLOT_BITS, NONE)
                hashes[slot[first]], values[slot[first]] = base[left[first]], scores[left[first]]
                self.tables.append((odd, hashes, values))
                left = np.delete(left, first)
                odd = (odd * 0xD1342543DE82EF95 + 2) & ((1 << 64) - 1) | 1
        return self.tables

    @staticmethod
    def _hash(text: str) -> int:
        out = 0
        for c in text:
            out = (out * 0x100000001B3 + ord(c) + 1) & ((1 << 64) - 1)
        return out

    def _solve(self, n: int, own: list[str]) -> None:
        codes = np.frombuffer("".join(own).encode("utf-32-le"), "<u4").reshape(len(own), n).T.astype(np.uint64)
        times, tables = np.uint64(0x100000001B3), self._table()
        best, back = np.full((n + 1, len(own)), NONE), np.zeros((n + 1, len(own)), np.int8)
        best[0] = 0.0
        for a in range(n):  # starts in rising order: of equal scores the earliest start stays
            h = np.zeros(len(own), np.uint64)
            for e in range(a + 1, min(n, a + self.longest) + 1):
                h = h * times + codes[e - 1] + np.uint64(1)
                score = np.full(len(own), NONE)
                for odd, hashes, values in tables:
                    slot = ((h * np.uint64(odd)) >> np.uint64(64 - SLOT_BITS)).astype(np.int64)
                    hit = hashes[slot] == h
                    score[hit] = values[slot[hit]]
                if e == a + 1:
                    score[score == NONE] = self.unknown
                score += best[a]
                better = score > best[e]
                best[e][better] = score[better]
                back[e][better] = a
        ids, unknown_ids = self.id.get, self.ids_of
        starts = back.T.tolist()
        for k, u in enumerate(own):
            out, e = [], n
            while e:
                a = starts[k][e]
                i = ids(u[a:e])
                if i is not None:
                    out.append(i)
                elif e == a + 1:
                    out += unknown_ids(u[a:e])[::-1]
                else:  # two strings of one hash: solve this one by itself
                    self.unit(u)
                    break
                e = a
            else:
                self.remember(u, np.array(out[::-1], "<u4").tobytes())

    def encode_all(self, texts: list[str]) -> list[bytes]:
        """Packed ids of several texts."""
        self.room()
        get = self.known.get
        rows = [self.units.findall(self.escaped(t)) for t in texts]
        found = [list(map(get, row)) for row in rows]
        self.learn({u for row, got in zip(rows, found) if None in got for u, g in zip(row, got) if g is None})
        unit = self.unit
        return [b"".join([g or unit(u) for u, g in zip(row, got)] if None in got else got) for row, got in zip(rows, found)]

    def encode(self, text: str | None) -> np.ndarray:
        return np.frombuffer(self.encode_all([text or ""])[0], "<u4")

    def decode(self, ids: np.ndarray) -> str:
        text = b"".join(map(self.raw.__getitem__, ids.tolist())).decode("utf-8", "replace").replace(SPACE, " ")
        return text[1:] if self.prefix and text.startswith(" ") else text

    # Chunks of one document.  State s at a cut: the last boundary is s characters before it.

    def parts(self, left: str, chunk: str) -> tuple[list[str], int, int] | None:
        """(units, first and last forced boundary) of a chunk, counted from its begin; null if it has none but perhaps its end."""
        units = self.units.findall(chunk)
        first = 0 if not left or self.forced(left[-1], chunk[0]) else len(units[0])
        last = len(chunk) - len(units[-1])
        return (units, first, last) if first <= last and first < len(chunk) else None

    def matrix(self, left: str, chunk: str) -> np.ndarray:
        """T[s, t]: best score from boundary -s to boundary len - t, with none in (-s, 0] nor in (len - t, len].

        Only differences within a matrix count.  Between a chunk's first and last
        forced boundary all paths share one best score, which is left out.
        """
        k, n, w = self.longest, len(chunk), len(left)
        text = left + chunk
        out = np.full((k, k), NONE)
        if found := self.parts(left, chunk):
            _, first, last = found
            enter = np.full(k, NONE)
            if first == 0:
                enter[0] = 0.0
            else:
                head = text[: w + first]
                for s in range(min(k, w + 1)):
                    best, _ = self.forward(head[w - s :], {0: 0.0}, s + 1)
                    enter[s] = best[-1]
            leave = np.full(k, NONE)
            best, _ = self.forward(chunk[last:], {0: 0.0}, 1)
            for t in range(min(k, n - last + 1)):
                leave[t] = best[n - last - t]
            return enter[:, None] + leave[None, :]
        for s in range(min(k, w + 1)):
            best, _ = self.forward(text[w - s :], {0: 0.0}, s + 1)
            for t in range(min(k, n)):
                out[s, t] = best[s + n - t]
        return out

    def trace(self, left: str, chunk: str, enter: np.ndarray) -> tuple[bytes, list[bytes | None], list[int]]:
        """Given the score of every state at the chunk's begin: the ids that all of its paths share, and for each state at its end the ids after those and the state the path comes from."""
        k, n, w = self.longest, len(chunk), len(left)
        text = left + chunk
        init = {w - s: float(enter[s]) for s in range(min(k, w + 1)) if enter[s] > NONE}
        if found := self.parts(left, chunk):
            units, first, last = found
            if first == 0:
                shared, source = b"", 0
                inner = units
            else:
                head = text[: w + first]
                _, back = self.forward(head, init, w + 1)
                cuts, begin = self.path(head, back, w + first)
                shared, source, inner = self.ids_on(head, cuts), w - begin, units[1:]
            shared += b"".join(map(self.unit, inner[:-1]))
            tail = chunk[last:]
            best, back = self.forward(tail, {0: 0.0}, 1)
            ends = [self.ids_on(tail, self.path(tail, back, n - last - t)[0]) if t <= n - last and best[n - last - t] > NONE else None for t in range(k)]
            return shared, ends, [source] * k
        best, back = self.forward(text, init, w + 1)
        ends, sources = [], []
        for t in range(k):
            if t >= n or best[w + n - t] == NONE:
                ends.append(None)
                sources.append(-1)
            else:
                cuts, begin = self.path(text, back, w + n - t)
                ends.append(self.ids_on(text, cuts))
                sources.append(w - begin)
        return b"", ends, sources


def product(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Max-plus product of (stacks of) matrices."""
    return (a[..., :, :, None] + b[..., None, :, :]).max(-2)


def scan(matrices: np.ndarray) -> np.ndarray:
    """Scores of the states at the begin of each chunk (from state 0 at the first), by a balanced tree of products: pairs are combined upwards, vectors handed down."""
    n, k = len(matrices), matrices.shape[1]
    start = np.full((1, k), NONE)
    start[0, 0] = 0.0
    levels = [matrices]
    while len(levels[-1]) > 1:
        m = levels[-1]
        even = len(m) // 2 * 2
        pairs = product(m[0:even:2], m[1:even:2])
        pairs -= np.where(np.isfinite(top := pairs.max((1, 2), keepdims=True)), top, 0.0)  # only differences count
        levels.append(np.concatenate([pairs, m[even:]]))
    for m in levels[-2::-1]:
        out = np.full((len(m), k), NONE)
        out[0::2] = start[: len(out[0::2])]
        odd = len(m) // 2
        v = (start[:odd, :, None] + m[0 : 2 * odd : 2]).max(1)
        out[1::2] = v - v.max(1, keepdims=True)
        start = out
    return start[:n]


_KINDS = {"ids": (pa.binary(), "binary"), "n_chunks": (pa.int64(), "bigint"), "n_pieces": (pa.int64(), "bigint"), "ids_crc32": (pa.int64(), "bigint"), "decoded_sha256": (pa.string(), "string")}
DIGEST = ("n_pieces", "ids_crc32", "n_chunks", "decoded_sha256")


def _schema(columns: tuple[str, ...]) -> str:
    return ", ".join(["doc_id bigint", *[f"{c} {_KINDS[c][1]}" for c in columns]])


def _columns(own: Pieces, blobs: list[bytes], n_chunks: list[int], columns: tuple[str, ...]) -> dict[str, list]:
    """What is asked for of each document's packed ids."""
    make = {
        "ids": lambda: blobs,
        "n_chunks": lambda: n_chunks,
        "n_pieces": lambda: [len(b) // 4 for b in blobs],
        "ids_crc32": lambda: [zlib.crc32(b) for b in blobs],
        "decoded_sha256": lambda: [hashlib.sha256(own.decode(np.frombuffer(b, "<u4")).encode()).hexdigest() for b in blobs],
    }
    return {c: make[c]() for c in columns}


def encode(docs: DataFrame, model: str, id_col: str = "doc_id", text_col: str = "text", chunk: int = CHUNK, columns: tuple[str, ...] = ("ids", "n_chunks")) -> DataFrame:
    """One row per input row: doc_id and the columns asked for: ids (packed unsigned 32-bit numbers), n_chunks, n_pieces, ids_crc32, decoded_sha256.

    Null and empty texts have no ids; documents of at most `chunk` characters
    are one chunk; repeated rows are repeated; only the two named columns are
    read; an empty table gives no rows.  U+2581 in a text reads as a space.
    """
    if chunk < 64:
        raise ValueError("chunks must be longer than any piece")
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    spread = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def plain(batches):
        own = Pieces.at(model)
        for batch in batches:
            for a, b in slices(batch.column(1)):
                blobs = own.encode_all(batch.column(1).slice(a, b - a).to_pylist())
                found = _columns(own, blobs, [1] * (b - a), columns)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), *[pa.array(found[c], _KINDS[c][0]) for c in columns]], names=["doc_id", *columns])

    small = rows.where(F.length("text") <= chunk).mapInArrow(tidy(plain, "pieces"), _schema(columns))

    def cut(batches):
        own = Pieces.at(model)
        for batch in batches:
            for k in range(batch.num_rows):
                row, doc, text = (c[k].as_py() for c in batch.columns)
                text = own.escaped(text)
                at = list(range(0, len(text), chunk))
                for a in range(0, len(at), 16):
                    some = at[a : a + 16]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([row] * len(some), pa.int64()), pa.array([doc] * len(some), pa.int64()), pa.array([x // chunk for x in some], pa.int64()), pa.array([text[max(0, x - own.longest + 1) : x] for x in some], pa.string()), pa.array([text[x : x + chunk] for x in some], pa.string())],
                        names=["row", "doc_id", "k", "head", "body"],
                    )

    giants = rows.where(F.length("text") > chunk).withColumn("row", F.monotonically_increasing_id()).select("row", "doc_id", "text")
    chunks = materialise(giants.mapInArrow(tidy(cut, "pieces"), "row bigint, doc_id bigint, k bigint, head string, body string").repartition(F.col("row"), F.col("k")), "chunks")

    def matrices(batches):
        own = Pieces.at(model)
        for batch in batches:
            for a, b in slices(batch.column(3)):
                part = batch.slice(a, b - a)
                found = [own.matrix(left, text).tobytes() for left, text in zip(part.column(2).to_pylist(), part.column(3).to_pylist())]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(found, pa.binary())], names=["row", "k", "m"])

    def combine(key, part):
        part = part.sort_values("k")
        size = Pieces.at(model).longest
        states = scan(np.stack([np.frombuffer(m, np.float64).reshape(size, size) for m in part["m"]]))
        part["enter"] = [s.tobytes() for s in states]
        return part[["row", "k", "enter"]]

    # Matrices are small, so their partitions would be merged into one; a number of them, given, keeps the work dealt.
    dealt = chunks.select("row", "k", "head", "body").mapInArrow(tidy(matrices, "pieces"), "row bigint, k bigint, m binary").repartition(spread, "row")
    entered = dealt.groupBy("row").applyInPandas(combine, "row bigint, k bigint, enter binary")

    def traces(batches):
        own = Pieces.at(model)
        for batch in batches:
            for a, b in slices(batch.column(4)):
                part = batch.slice(a, b - a)
                left, text, enter = [c.to_pylist() for c in part.columns[3:]]
                own.room()
                own.learn({u for t in text for u in own.units.findall(t)} - own.known.keys())
                got = [own.trace(x, y, np.frombuffer(e, np.float64)) for x, y, e in zip(left, text, enter)]
                yield pa.RecordBatch.from_arrays(
                    [*part.columns[:3], pa.array([g[0] for g in got], pa.binary()), pa.array([g[1] for g in got], pa.list_(pa.binary())), pa.array([g[2] for g in got], pa.list_(pa.int64()))],
                    names=["row", "doc_id", "k", "shared", "ends", "sources"],
                )

    traced = chunks.join(entered, ["row", "k"]).select("row", "doc_id", "k", "head", "body", "enter").mapInArrow(tidy(traces, "pieces"), "row bigint, doc_id bigint, k bigint, shared binary, ends array<binary>, sources array<bigint>")

    def put_together(part):
        import pandas as pd

        part = part.sort_values("k")
        out, state = [], 0
        for shared, ends, sources in zip(part["shared"][::-1], part["ends"][::-1], part["sources"][::-1]):
            out.append(bytes(shared) + bytes(ends[state]))
            state = int(sources[state])
        return pd.DataFrame({"doc_id": part["doc_id"].iloc[:1].to_numpy(), **_columns(Pieces.at(model), [b"".join(out[::-1])], [len(part)], columns)})

    large = traced.groupBy("row").applyInPandas(put_together, _schema(columns))
    return small.unionByName(large)


def decode(encoded: DataFrame, model: str) -> DataFrame:
    """Rows of encode() with their text."""

    def run(batches):
        own = Pieces.at(model)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([own.decode(np.frombuffer(b, "<u4")) for b in batch.column(1).to_pylist()], pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(tidy(run, "pieces"), "doc_id bigint, text string")


def digest(encoded: DataFrame, model: str, with_ids: bool = False) -> DataFrame:
    """Of rows of encode(): doc_id, n_pieces, ids_crc32, n_chunks, the SHA-256 of the decoded text, and the packed ids if asked for."""
    columns = DIGEST + ("ids",) * with_ids

    def run(batches):
        own = Pieces.at(model)
        for batch in batches:
            for a, b in slices(batch.column(1)):
                part = batch.slice(a, b - a)
                found = _columns(own, part.column(1).to_pylist(), part.column(2).to_pylist(), columns)
                yield pa.RecordBatch.from_arrays([part.column(0), *[pa.array(found[c], _KINDS[c][0]) for c in columns]], names=["doc_id", *columns])

    return encoded.select("doc_id", "ids", "n_chunks").mapInArrow(tidy(run, "pieces"), _schema(columns))
