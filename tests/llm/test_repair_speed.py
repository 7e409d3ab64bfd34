"""Runs with several marks and odd white space are encoded like whole texts."""

import numpy as np
import public_tokenizers

from tilebalance.llm import repair

PATH = public_tokenizers.path("word_bpe_49k.json")


def test_several_marks_are_cut_off():
    own = repair.Encoder(PATH)
    asked = []
    own.learn_runs = lambda words, f=own.learn_runs: (asked.extend(words), f(words))
    texts = ["Queen### menté.*** a1%%% it's!! x-y... ***", "queen*** menté### A1!! ###", "don't.## ?! a|b## 日本。## ß$$$ <|x|>##"]
    assert [np.frombuffer(x, own.kind).tolist() for x in own.encode(texts)] == [own.ids(t) for t in texts]
    assert not {"queen###", "queen***", "menté.***", "menté###"} & {*asked}


def test_separators_beside_white_space():
    own = repair.Encoder(PATH)
    texts = ["\x1c a b ", " a\x1d b\x1f \n", "\x1e", "  ", ""]
    assert [np.frombuffer(x, own.kind).tolist() for x in own.encode(texts)] == [own.ids(t) for t in texts]
