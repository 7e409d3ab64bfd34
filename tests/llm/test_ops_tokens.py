import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pytest

from tests.llm.fixtures import documents, empty
from tilebalance.llm import attribution, pieces
from tilebalance.llm.common import slices

MODEL = public_tokenizers.path("piece_bpe_32k.model")
BPE, PATTERN = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


@pytest.fixture(scope="module")
def own():
    return pieces.Pieces(MODEL)


@pytest.fixture(scope="module")
def library():
    """The library on the same pieces, its model kind set to the unigram lattice."""
    import sentencepiece

    data = bytearray(open(MODEL, "rb").read())
    place, inner = next((p, v) for n, p, v in pieces._fields(bytes(data)) if n == 2)
    at = next(p for n, p, _ in pieces._fields(inner) if n == 3)
    assert data[place + at] == 2
    data[place + at] = 1
    return sentencepiece.SentencePieceProcessor(model_proto=bytes(data))


def texts():
    rnd = random.Random(8)
    letters = "etaoin shrdlu ENT äöñé the of and ing"
    return ["".join(rnd.choice(letters) for _ in range(rnd.randrange(1, 60))) for _ in range(300)] + ["Hello world", "a", " lead", "trail  ", "x" * 40, "thethethethethe" * 3]


def test_scores_equal_the_librarys_lattice(own, library):
    """The library's best of several paths has our score; its single-path shortcut is never better."""
    score = lambda ids: sum(own.pieces[i][1] for i in ids)
    alike = 0
    for t in texts():
        if "  " in t:
            continue
        ids = own.encode(t).tolist()
        assert score(ids) >= score(library.encode(t))
        assert library.decode(ids) == own.decode(np.array(ids)) == t
        if len(t) < 12:
            assert score(ids) == score(library.nbest_encode_as_ids(t, 3)[0])
        alike += ids == library.encode(t)
    assert alike > 140


def brute(own, text):
    """Plain dynamic programme over the whole text."""
    text = own.escaped(text)
    _, back = own.forward(text, {0: 0.0}, 1)
    return np.frombuffer(own.ids_on(text, own.path(text, back, len(text))[0]), "<u4")


def chunked(own, text, size):
    text = own.escaped(text)
    parts = [(text[max(0, a - own.longest + 1) : a], text[a : a + size]) for a in range(0, len(text), size)]
    states = pieces.scan(np.stack([own.matrix(*p) for p in parts]))
    out, state = [], 0
    for p, s in list(zip(parts, states))[::-1]:
        shared, ends, sources = own.trace(*p, s)
        out.append(shared + ends[state])
        state = sources[state]
    return np.frombuffer(b"".join(out[::-1]), "<u4")


def test_chunks_equal_the_whole(own):
    rnd = random.Random(1)
    samples = [" ".join(texts()[:40]), "ab" * 700, "日本語" * 200, "theinerst" * 150, "x\n\n  y" * 100]
    samples += ["".join(rnd.choice("therstino") for _ in range(900)) for _ in range(6)]
    for t in samples:
        whole = brute(own, t)
        assert own.encode(t).tolist() == whole.tolist()
        assert own.decode(whole) == t
        for size in (16, 17, 33, 200):
            assert chunked(own, t, size).tolist() == whole.tolist()


def test_scan_is_the_sequential_product():
    rnd = np.random.default_rng(3)
    for n in (1, 2, 3, 7, 16, 33):
        m = rnd.integers(-9, 0, (n, 4, 4)).astype(float)
        v = np.array([0.0, -np.inf, -np.inf, -np.inf])
        for k, s in enumerate(pieces.scan(m)):
            assert np.allclose((s - s.max())[np.isfinite(s)], (v - v.max())[np.isfinite(v)])
            v = (v[:, None] + m[k]).max(0)


@pytest.mark.parametrize("chunk", [64, 16384])
def test_piece_operator(spark, own, chunk):
    docs = documents(spark)
    rows = [(r.doc_id, r.text or "") for r in docs.collect()]
    want = sorted((str(i), zlib.crc32(own.encode(t).tobytes()), hashlib.sha256(t.encode()).hexdigest()) for i, t in rows)
    got = pieces.digest(pieces.encode(docs, MODEL, chunk=chunk), MODEL).collect()
    assert sorted((str(r.doc_id), r.ids_crc32, r.decoded_sha256) for r in got) == want
    assert max(r.n_chunks for r in got) > 1 if chunk == 64 else True
    assert pieces.encode(empty(spark), MODEL).count() == 0


@pytest.mark.parametrize("rule", attribution.RULES)
def test_allocation_against_brute_force(rule):
    rnd = random.Random(6)
    for _ in range(200):
        cuts = sorted(rnd.sample(range(60), 8))
        a, b = np.array(cuts[0::2]), np.array(cuts[1::2])
        ends = np.cumsum([rnd.randrange(1, 9) for _ in range(9)])
        begins = np.concatenate([[0], ends[:-1]])
        got, crossing = attribution.allocate(begins, ends, a, b, rule)
        for s, e, g, c in zip(begins, ends, got, crossing):
            touched = [k for k in range(4) if min(e, b[k]) > max(s, a[k])]
            assert c == (len(touched) > 1)
            want = -1 if not touched else touched[0] if rule == "first" else touched[-1] if rule == "last" else max(touched, key=lambda k: (min(e, b[k]) - max(s, a[k]), -k))
            assert g == want


def test_attribution_operator(spark):
    import tiktoken

    enc, _ = attribution.encoding(BPE, PATTERN)
    docs = documents(spark)
    rows = {}
    for r in docs.collect():
        rows.setdefault(r.doc_id, []).append(r.text or "")
    got = attribution.attribute(docs, BPE, PATTERN).collect()
    assert len(got) == docs.count()
    for r in got:
        options = [(len(enc.encode_ordinary(t)), t.count("\n") + 1) for t in rows[r.doc_id]]
        assert (r.n_tokens, r.n_sections) in options and sum(r.section_tokens) + r.n_outside == r.n_tokens == sum(r.section_tokens) + r.n_outside
    two = attribution.attribute(docs, BPE, PATTERN, fields=("source", "text"), joint=" ", by="fields").collect()
    assert all(r.n_sections == 2 and sum(r.section_tokens) + r.n_outside == r.n_tokens for r in two)
    assert attribution.attribute(empty(spark), BPE, PATTERN).count() == 0
    text = "naïve 日本語\U0001f600 x"
    ids, a, b = attribution.token_spans(text, BPE, PATTERN)
    assert b[-1] == len(text) and (a[1:] <= b[:-1]).all() and (a < b).all() and isinstance(enc, tiktoken.Encoding)


def test_columns_made_while_encoding_equal_those_made_after(spark):
    docs = documents(spark)
    after = pieces.digest(pieces.encode(docs, MODEL, chunk=512), MODEL, with_ids=True)
    made = pieces.encode(docs, MODEL, chunk=512, columns=(*pieces.DIGEST, "ids"))
    assert made.columns == after.columns
    assert sorted(map(str, made.collect())) == sorted(map(str, after.collect()))


def test_forgetting_stretches_changes_no_ids():
    text = [" ".join(chr(97 + i % 26) * (1 + j) + "ing" for j in range(1 + i // 26)) for i in range(300)]
    few, many = pieces.Pieces(MODEL, limit=1), pieces.Pieces(MODEL)
    assert [few.encode_all(text[a : a + 20]) for a in range(0, 300, 20)] == [many.encode_all(text[a : a + 20]) for a in range(0, 300, 20)]
    assert few.held < many.held


def test_slices_are_bounded_by_bytes():
    import pyarrow as pa

    texts = pa.array(["a" * 10, None, "b" * 5, "c" * 100, "d" * 3, "", "e" * 12])
    got = list(slices(texts, 15))
    assert got == [(0, 3), (3, 4), (4, 7)] and list(slices(texts.slice(0, 0), 15)) == []
