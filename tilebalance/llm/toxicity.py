"""Toxic spans by a two-state linear-chain conditional random field.

Tokens are the runs between white space of the lower-cased text.  A token's
features are its word (punctuation stripped) and the word's prefixes of 4 to 8
letters.  Token labels come from the document labels: within documents labelled
toxic, a token is labelled 1 if one of its features is much commoner in toxic
than in other documents of the fitting sample; every other token is labelled 0.
The field (feature weights, transitions) is fitted by gradient ascent on the
conditional likelihood, on two thirds of the sample; on the last third a
logistic curve is fitted that turns a document's forward-backward marginals
(their largest, their sum, their share) into its score.

Fitting uses a bounded sample: at most `per_class` labelled rows of each class,
those with the smallest MD5 of their id, of at most `max_chars` characters.
Scoring covers every row and whole texts.
"""

from __future__ import annotations

import math
import re
import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import give_back, make_room, slices, tidy

PER_CLASS, MAX_CHARS = 2000, 30_000
PREFIXES, FEATURE_BITS = range(4, 9), 20
WIDTH = 1 + len(PREFIXES)
_EDGE = re.compile(r"^[\W_]+|[\W_]+$")
_CACHE_LIMIT = 200_000


def held_out(doc_id: Column) -> Column:
    """True where crc32 of the id as text is a multiple of 5."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def features(token: str) -> list[int]:
    """WIDTH numbers from 0 (no feature) to 2**FEATURE_BITS: hashes of the word and its prefixes."""
    word = _EDGE.sub("", token)
    if not word:
        return [0] * WIDTH
    own = [f"={word}", *[word[:k] for k in PREFIXES if len(word) >= k]]
    return [(zlib.crc32(f.encode("utf-8", "replace")) >> (32 - FEATURE_BITS)) + 1 for f in own] + [0] * (WIDTH - len(own))


@dataclass
class Field:
    """Fitted weights; all plain numbers, so that it can be sent to tasks (its size is bounded by the fitting sample's)."""

    weights: np.ndarray  # float32, 2**FEATURE_BITS + 1
    bias: float
    trans: tuple[float, float, float, float]  # log weights 00, 01, 10, 11
    curve: tuple[float, ...]
    prior: float = 0.0
    cache: dict[str, float] = field(default_factory=dict)

    def __getstate__(self):
        return self.__dict__ | {"cache": {}}

    def emission(self, token: str) -> float:
        """exp of the log weight of state 1 against state 0."""
        found = self.cache.get(token)
        if found is None:
            if len(self.cache) >= _CACHE_LIMIT:
                self.cache.clear()
            w = self.weights
            found = self.cache[token] = math.exp(max(-30.0, min(30.0, self.bias + sum(float(w[f]) for f in features(token)))))
        return found

    def marginals(self, texts: list[str | None]) -> list[np.ndarray]:
        """P(token is toxic) for the tokens of each text."""
        cached, emission = self.cache.get, self.emission
        rows = []
        for text in texts:
            words = (text or "").lower().split()
            got = list(map(cached, words))
            if None in got:
                got = [emission(w) if g is None else g for w, g in zip(words, got)]
            rows.append(got)
        lengths = np.fromiter(map(len, rows), np.int64, len(rows))
        starts = np.concatenate([[0], np.cumsum(lengths)])
        flat = np.fromiter((e for r in rows for e in r), np.float64, int(starts[-1]))
        p = chain_marginals(flat, starts[:-1], lengths, self.trans)
        return [p[a : a + n] for a, n in zip(starts, lengths)]

    def score(self, p: np.ndarray) -> float:
        return 1.0 / (1.0 + math.exp(-max(-30.0, min(30.0, float(np.dot(self.curve, doc_features(p)))))))


def doc_features(p: np.ndarray) -> np.ndarray:
    if not len(p):
        return np.array([1.0, 0.0, 0.0, 0.0])
    total = float(p.sum())
    return np.array([1.0, float(p.max()), math.log1p(total), min(1.0, 20 * total / (len(p) + 20))])


def chain_marginals(e: np.ndarray, starts: np.ndarray, lengths: np.ndarray, trans: tuple[float, float, float, float]) -> np.ndarray:
    """Forward-backward over many chains in step: what is carried is the ratio of state 1 to state 0.  e holds exp(emissions), chain after chain."""
    t00, t01, t10, t11 = (math.exp(t) for t in trans)
    ratio, back = np.empty_like(e), np.ones_like(e)
    order = np.argsort(-lengths, kind="stable")
    begin, size = starts[order], lengths[order]
    few = int((size > 0).sum())
    steps = int(size[16]) if len(size) > 16 else 0  # the longest 16 chains go on alone from here
    r = np.zeros(few)
    for t in range(steps):
        k = int(np.searchsorted(-size, -t, side="left"))
        at = begin[:k] + t
        r = e[at] if t == 0 else e[at] * (t01 + r[:k] * t11) / (t00 + r[:k] * t10)
        r = np.clip(r, 1e-300, 1e300)
        ratio[at] = r
    for c in range(min(16, few)):
        a, n = int(begin[c]), int(size[c])
        own, x = e[a : a + n].tolist(), float(ratio[a + steps - 1]) if steps else 0.0
        out = []
        for t in range(steps, n):
            x = own[t] if t == 0 else own[t] * (t01 + x * t11) / (t00 + x * t10)
            x = min(max(x, 1e-300), 1e300)
            out.append(x)
        ratio[a + steps : a + n] = out
        y, out = 1.0, []
        for t in range(n - 2, -1, -1):
            y = own[t + 1] * y
            y = (t10 + t11 * y) / (t00 + t01 * y)
            out.append(y)
        back[a : a + n - 1] = out[::-1]
    if few > 16:
        first, last = begin[16:few], size[16:few]
        b = np.ones(few - 16)
        for t in range(steps - 2, -1, -1):
            k = int(np.searchsorted(-last, -(t + 1), side="left"))  # chains with a token t + 1
            at = first[:k] + t
            y = e[at + 1] * b[:k]
            b[:k] = (t10 + t11 * y) / (t00 + t01 * y)
            back[at] = b[:k]
    odds = ratio * back
    return odds / (1.0 + odds)


def telling(words: np.ndarray, docs: list[np.ndarray], toxic: list[int], least: int = 4, times: float = 6.0) -> np.ndarray:
    """Which features are much commoner in toxic documents (in at least `least` of them): the weak labels of tokens.  words has the features of each word, docs the words of each document."""
    seen = np.zeros((2, (1 << FEATURE_BITS) + 1))
    for own, y in zip(docs, toxic):
        seen[y][np.unique(words[np.unique(own)])] += 1
    n0, n1 = max(1, toxic.count(0)), max(1, toxic.count(1))
    out = (seen[1] >= least) & (seen[1] / n1 >= times * (seen[0] + 0.5) / n0)
    out[0] = False
    return out


def fit(texts: list[str], toxic: list[int], share: float, rounds: int = 60, piece: int = 96) -> Field:
    """Fit on a sample; share is the toxic share among all labelled rows, to which the score is set."""
    size = (1 << FEATURE_BITS) + 1
    ones = sum(toxic)
    if not ones or ones == len(toxic):  # nothing to tell apart: a constant score
        p = min(0.999, max(0.001, ones / len(toxic) if toxic else 0.0))
        return Field(np.zeros(size, np.float32), -30.0, (0.0, 0.0, 0.0, 0.0), (math.log(p / (1 - p)), 0.0, 0.0, 0.0))
    train = [i for i in range(len(texts)) if i % 3]
    number: dict[str, int] = {}
    docs = [np.array([number.setdefault(w, len(number)) for w in (texts[i] or "").lower().split()], np.int32) for i in train]
    words = np.array([features(w) for w in number] or [[0] * WIDTH], np.int32)
    number.clear()
    marked = telling(words, docs, [toxic[i] for i in train])[words].any(1)
    held = np.zeros(size, np.int32)
    for own in docs:
        held[np.unique(words[np.unique(own)])] += 1
    words[held[words] < 3] = 0
    parts, marks = [], []
    for i, own in zip(train, docs):
        for a in range(0, len(own), piece):
            y = marked[own[a : a + piece]] & bool(toxic[i])
            if y.any() or (a // piece + i) % 4 == 0:  # of pieces without a 1, a quarter by position
                parts.append(own[a : a + piece])
                marks.append(y)
    order = sorted(range(len(parts)), key=lambda k: -len(parts[k]))
    n = np.array([len(parts[k]) for k in order], np.int64)
    x, y = np.zeros((piece, len(order)), np.int32), np.zeros((piece, len(order)), np.int8)
    for c, k in enumerate(order):
        x[: n[c], c], y[: n[c], c] = parts[k], marks[k]
    active = [int((n > t).sum()) for t in range(piece)]
    mask = np.arange(piece)[:, None] < n[None, :]
    theta, trans, bias = np.zeros(size), np.zeros(4), -3.0
    m, v = np.zeros(size + 5), np.zeros(size + 5)
    pairs = np.zeros(4)
    for t in range(1, piece):
        k = active[t]
        pairs += np.bincount(2 * y[t - 1, :k] + y[t, :k], minlength=4)[:4]
    total = max(1.0, float(mask.sum()))
    for step in range(1, rounds + 1):
        em = np.exp(np.clip(bias + theta[words].sum(1), -30, 30))[x]
        t00, t01, t10, t11 = np.exp(trans)
        a, b = np.zeros_like(em), np.ones_like(em)
        a[0] = em[0]
        for t in range(1, piece):
            k = active[t]
            a[t, :k] = np.clip(em[t, :k] * (t01 + a[t - 1, :k] * t11) / (t00 + a[t - 1, :k] * t10), 1e-200, 1e200)
        expected = np.zeros(4)
        for t in range(piece - 2, -1, -1):
            k = active[t + 1]
            s = em[t + 1, :k] * b[t + 1, :k]
            w = np.stack([np.full(k, t00), t01 * s, a[t, :k] * t10, a[t, :k] * t11 * s])
            expected += (w / w.sum(0)).sum(1)
            b[t, :k] = (t10 + t11 * s) / (t00 + t01 * s)
        odds = a * b
        error = np.where(mask, y - odds / (1 + odds), 0.0)
        by_word = np.bincount(x.ravel(), weights=error.ravel(), minlength=len(words))
        slope = np.bincount(words.ravel(), weights=np.repeat(by_word, WIDTH), minlength=size)
        slope[0] = 0
        g = np.concatenate([slope / total * 100 - 1e-3 * theta, [error.sum() / total * 100], (pairs - expected) / total * 100 - 1e-3 * trans])
        m, v = 0.8 * m + 0.2 * g, 0.95 * v + 0.05 * g * g
        move = 0.3 * (m / (1 - 0.8**step)) / (np.sqrt(v / (1 - 0.95**step)) + 1e-4)
        theta += move[:size]
        bias += move[size]
        trans += move[-4:]
    theta[0] = 0.0
    model = Field(theta.astype(np.float32), float(bias), tuple(map(float, trans)), (0.0,) * 4)
    rest = [i for i in range(len(texts)) if i % 3 == 0]
    t = np.array([toxic[i] for i in rest], float)
    if not 0 < t.sum() < len(t):
        rest, t = list(range(len(texts))), np.array(toxic, float)
    z = np.array([doc_features(p) for p in model.marginals([texts[i] for i in rest])])
    weight = np.where(t > 0, share / max(t.mean(), 1e-9), (1 - share) / max(1 - t.mean(), 1e-9))
    curve = np.zeros(4)
    for _ in range(50):  # Newton's method with a small ridge
        q = 1 / (1 + np.exp(-np.clip(z @ curve, -30, 30)))
        h = (z * (weight * q * (1 - q))[:, None]).T @ z + 0.05 * np.eye(4)
        delta = np.linalg.solve(h, z.T @ (weight * (t - q)) - 0.05 * curve)
        curve += np.clip(delta, -5, 5)
    model.curve = tuple(map(float, curve))
    model.cache.clear()
    return model


def sample(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS, max_chars: int = MAX_CHARS) -> tuple[DataFrame, DataFrame]:
    """(fitting rows (doc_id, text, toxic), counts by class) of labelled rows that are not held out.  Of several labels of one id the largest counts."""
    own = labels.where("doc_id is not null and toxic in (0, 1)").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic")).where(~held_out(F.col("doc_id")))
    ids = docs.where(F.length("text") <= max_chars).select(F.col("doc_id").cast("bigint").alias("doc_id"))
    first = [
        ids.join(own.where(F.col("toxic") == y), "doc_id").distinct().withColumn("h", F.md5(F.col("doc_id").cast("string").cast("binary"))).orderBy("h", "doc_id").limit(per_class)
        for y in (0, 1)
    ]
    chosen = first[0].unionByName(first[1])  # at most 2 * per_class rows
    rows = docs.where(F.length("text") <= max_chars).select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.first("toxic").alias("toxic"), F.first("h").alias("h"))
    return rows, own.groupBy("toxic").count()


def train(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS, max_chars: int = MAX_CHARS) -> Field:
    rows, counts = sample(docs, labels, per_class, max_chars)
    got = sorted(rows.collect(), key=lambda r: (r.h, r.doc_id))  # bounded by per_class and max_chars
    by = {r.toxic: r["count"] for r in counts.collect()}
    share = by.get(1, 0) / max(1, sum(by.values()))
    return fit([r.text for r in got], [r.toxic for r in got], min(0.99, max(0.01, share)))


def score_column(model: Field):
    """A column function: text -> score, over whole texts."""

    @F.arrow_udf("double")
    def run(texts: pa.Array) -> pa.Array:
        make_room()
        out: list[float] = []
        for a, b in slices(texts):
            out += [model.score(p) for p in model.marginals(texts.slice(a, b - a).to_pylist())]
        give_back()
        return pa.array(out, pa.float64())

    return run


def offending(text: str | None, p: np.ndarray, at: float) -> list[dict]:
    """Character offsets and marginals of the tokens that are toxic with probability `at` or more."""
    lower = (text or "").lower()
    if not len(p) or p.max() < at:
        return []
    same = len(lower) == len(text)  # lower-casing lengthens a few characters; offsets are then found in the text itself
    tokens = re.finditer(r"\S+", lower if same else text)
    return [{"start": m.start(), "end": m.end(), "p": float(q)} for m, q in zip(tokens, p) if q >= at]


def score_documents(docs: DataFrame, model: Field, id_col: str = "doc_id", text_col: str = "text", spans: bool = False, span_at: float = 0.5) -> DataFrame:
    """One row per input row: doc_id, score (and spans: start, end, p of offending tokens as character offsets).

    Null and empty texts have no tokens and get the score of an empty
    chain; long texts are scored whole; repeated rows get equal scores;
    only the two named columns are read; an empty table gives no rows.
    """
    kind = "doc_id bigint, score double" + ", spans array<struct<start:bigint,end:bigint,p:double>>" * spans
    place = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("p", pa.float64())]))

    def run(batches):
        for batch in batches:
            for a, b in slices(batch.column(1)):
                texts = batch.column(1).slice(a, b - a).to_pylist()
                ps = model.marginals(texts)
                cols = [batch.column(0).slice(a, b - a), pa.array([model.score(p) for p in ps], pa.float64())]
                if spans:
                    cols.append(pa.array([offending(t, p, span_at) for t, p in zip(texts, ps)], place))
                yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "score", "spans"][: len(cols)])

    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(tidy(run), kind)
