import random
import re

import numpy as np
import pytest

from vintage.llm import queries
from vintage.llm.minhash_dedup import common, estimate, minima, near_duplicates, packed
from vintage.llm.words import shingle_sets

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute(texts, percent=85):
    """{id: (size, component)} by comparing all pairs of sets of word tuples."""
    sets = {}
    for k, t in texts:
        w = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
        sets[k] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
    ids, comp = sorted(sets), {k: k for k in sets}

    def top(k):
        while comp[k] != k:
            k = comp[k]
        return k

    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            x, y = sets[a], sets[b]
            if x and y and 100 * min(len(x), len(y)) >= percent * max(len(x), len(y)):
                n = len(x & y)
                if 100 * n >= percent * (len(x) + len(y) - n):
                    p, q = sorted((top(a), top(b)))
                    comp[q] = p
    return {k: (len(sets[k]), top(k)) for k in ids}


@pytest.mark.parametrize("size", ["sf0.001", "sf0.01"])
def test_whole_table(spark, size):
    d = f"/root/testdata/{size}"
    want = brute([(r.doc_id, r.text) for r in spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "text").collect()])
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in queries.op8_minhash_near_dedup(spark, d).collect()}
    assert got == want


def family(rng, n, words, edits):
    base = [f"w{rng.randint(0, 10**6)}" for _ in range(words)]
    out = []
    for _ in range(n):
        t = list(base)
        for _ in range(edits):
            t[rng.randrange(words)] = f"x{rng.randint(0, 10**6)}"
        out.append(" ".join(t))
    return out


def test_families_without_their_origin_and_chains(spark):
    """Copies too far from one another, copies linked through one, chains, and several blocks."""
    rng = random.Random(11)
    texts = family(rng, 60, 200, 5) + family(rng, 60, 200, 3) + family(rng, 40, 100, 1)
    chain = [f"c{k}" for k in range(300)]
    texts += [" ".join(chain[k : k + 200]) for k in range(0, 100, 4)]
    rows = list(enumerate(texts))
    got = {r.doc_id: r.component_id for r in near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), block=16).collect()}
    assert got == {k: c for k, (_, c) in brute(rows).items()}


def test_hard_rows(spark):
    rows = [(5, None, 1), (4, "", 1), (3, " \t\n", 1), (2, "One two", 1), (9, "one TWO", 1), (7, "a b c d e", 1), (8, "a b c d e", 1), (8, "a b c d e", 1), (None, "a b c d e", 1), (10, "é É x y z", 1), (11, "é é x y z", 1)]
    got = sorted((tuple(r) for r in near_duplicates(spark.createDataFrame(rows, "doc_id long, text string, digest int")).collect()), key=str)
    assert got == sorted([(5, 0, 5, True), (4, 0, 4, True), (3, 0, 3, True), (2, 1, 2, True), (9, 1, 2, False), (7, 1, 7, True), (8, 1, 7, False), (8, 1, 7, False), (None, 1, None, True), (10, 1, 10, True), (11, 1, 11, True)], key=str)
    assert near_duplicates(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_estimates_follow_similarity():
    rng = np.random.default_rng(1)
    for share in (0.5, 0.85, 0.95):
        errors = []
        for _ in range(60):
            both, a, b = (np.unique(rng.integers(0, 1 << 63, n, dtype=np.uint64)) for n in (int(400 * share), int(200 * (1 - share)), int(200 * (1 - share))))
            m = packed(minima([np.union1d(both, a), np.union1d(both, b)]))
            errors.append(float(estimate(m[0], m[1])) - len(both) / (len(both) + len(a) + len(b)))
        assert abs(np.mean(errors)) < 0.02


def test_common():
    sets = shingle_sets([b"a b c d e f g", b"b c d e f g h", b"x"])
    assert common(sets, sets).tolist() == [[len(np.intersect1d(x, y)) for y in sets] for x in sets]


def test_blocks_are_bounded_by_words(spark, monkeypatch):
    """The same classes where every block of a mixed bucket is cut to a few texts."""
    rng = random.Random(17)
    texts = family(rng, 30, 80, 3) + family(rng, 20, 400, 10)
    rows = list(enumerate(texts))
    want = brute(rows, 80)
    for words in (1 << 19, 300):
        monkeypatch.setattr("vintage.llm.minhash_dedup.BLOCK_WORDS", words)
        got = near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), percent=80).collect()
        assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == want
