"""Runs are cut into core and marks before they are looked up; texts of a call share the look-ups, documents' ends need no mark for each symbol."""

import numpy as np
import public_tokenizers

from tilebalance.llm import repair

PATH = public_tokenizers.path("word_bpe_49k.json")
ODD = [
    None, "", " \n", ".", "a.", "Queen, queen. QUEEN! queen", "é. É, naïve##", "x\x85y\xa0z w　v  u", "\x1ca b\x1c. \x1d", "日本。, ab. 日. 日",
    "½. x²! 9% _. a_, 'S it's! don't.##", "<|endoftext|>, Ab. <|x|>", "İstanbul. ŠKODA, œuvre! į. ĵ.", "á. é! ́.", "|, a| |a. |", "\x00. a\x00!",
]


def packed(own, texts):
    return [np.frombuffer(x, own.kind).tolist() for x in own.encode(texts)]


def test_runs_with_marks_are_not_remembered_beside_their_cores():
    own = repair.Encoder(PATH)
    texts = ["menté, menté. menté!! queen## queen", "queen, menté"]
    assert packed(own, texts) == [own.ids(t) for t in texts]
    assert {"queen", "menté", ","} <= {*own.known}
    assert not {"queen,", "queen##", "menté,", "menté.", "menté!!"} & {*own.known}


def test_texts_of_a_call_share_the_lookups():
    own = repair.Encoder(PATH)
    asked = []
    own.learn = lambda words, f=own.learn: (asked.extend(words), f(words))
    texts = ["Cloudberry, stra\xdfe.", "cloudberry. cloudberry! STRA\xdfE", None]
    assert packed(own, texts) == [own.ids(t or "") for t in texts]
    assert sorted(asked) == sorted({*asked}) and asked.count("cloudberry") == 1


def test_odd_texts_alone_together_and_after_forgetting():
    own = repair.Encoder(PATH, limit=3)
    want = [own.ids(t or "") for t in ODD]
    assert packed(own, ODD) == want
    assert [packed(own, [t])[0] for t in ODD] == want
    rnd = np.random.default_rng(5)
    marks = ["", ".", ",", "!!", "##", "'", "|", "½", "é", "日", "́", " ", "\xa0", "\x1d", "\x85", "S", "9", "_"]
    texts = ["".join(rnd.choice([w, m]) for w, m in zip(rnd.choice(["ab", "Stra\xdfe", "x1", "œ", "ª"], 40), rnd.choice(marks, 40))) for _ in range(300)]
    assert packed(own, texts) == [own.ids(t) for t in texts]
    assert packed(own, []) == []


def test_ends_of_documents_after_replacement():
    rnd = np.random.default_rng(7)
    docs = [np.append(rnd.integers(0, 3, n), 9) for n in rnd.integers(0, 40, 400)] + [np.array([9])] * 50 + [np.full(64, 1)]
    last = np.zeros(sum(map(len, docs)), bool)
    last[np.cumsum([len(d) for d in docs]) - 1] = True
    seq, rules, marks, _ = repair.compress(np.concatenate(docs), last, 10)

    def spell(s):
        return [s] if s < 10 else spell(int(rules[s - 10, 0])) + spell(int(rules[s - 10, 1]))

    parts = np.split(seq, np.flatnonzero(marks)[:-1] + 1)
    assert [sum((spell(int(s)) for s in p), []) for p in parts] == [d.tolist() for d in docs]
