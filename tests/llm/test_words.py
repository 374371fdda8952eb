import random
import re

import numpy as np

from vintage.llm import words

WORD = re.compile(rb"[^\x20\x09-\x0D]+")


def test_words_of_long_and_odd_buffers(monkeypatch):
    rng = random.Random(2)
    monkeypatch.setattr(words, "SEGMENT", 1 << 13)
    for _ in range(30):
        text = b"".join(rng.choice([b"a", b"bc", b" ", b"\n", b"\t ", b"x" * rng.choice([1, 50, 20_000]), "é\x1c ".encode()]) for _ in range(rng.choice([0, 1, 400])))
        h, s, e = words.word_hashes(np.frombuffer(text, np.uint8), lower=False)
        found = [(m.start(), m.end()) for m in WORD.finditer(text)]
        assert list(zip(s.tolist(), e.tolist())) == found
        by = {}
        for x, (i, j) in zip(h.tolist(), found):
            assert by.setdefault(text[i:j], x) == x
        assert len(set(by.values())) == len(by)


def test_shingle_sets_equal_sets_of_tuples():
    rng = random.Random(4)
    texts = [" ".join(rng.choice("aBcdE") for _ in range(rng.choice([0, 1, 4, 5, 30, 400]))).encode() for _ in range(200)]
    for t, s in zip(texts, words.shingle_sets(texts)):
        w = t.lower().split()
        assert len(s) == len({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
        assert (np.diff(s.astype(object)) > 0).all()
