import random

from vintage.llm import bpe, queries
from vintage.llm.token_counts import EDITS, VOCABULARY, CountTree, apply_edits, attach_edits, build_trees, word_counter

PARTS = ["a", " ", "  ", "\n", "'", "'s", "'ll", "word", " words", "12", "é", "²", "...", "日", "\U0001f600", "\x1c", "   x", "\t"]


def test_random_edits_equal_counting_afresh():
    counter, rng = word_counter(), random.Random(7)
    for _ in range(300):
        text = "".join(rng.choice(PARTS) for _ in range(rng.choice([0, 3, 40, 900])))
        tree = CountTree.of(text, counter)
        for _ in range(12):
            start, length, new = rng.randint(-2, len(text) + 2), rng.choice([0, 0, 1, 3, 50]), "".join(rng.choice(PARTS) for _ in range(rng.randint(0, 5)))
            s = min(max(start, 0), len(text))
            text = text[:s] + new + text[s + min(length, len(text) - s) :]
            tree.edit(start, length, new)
            fresh = CountTree.of(text, counter)
            assert tree.text == text
            assert [x for b in tree.lengths for x in b] == [x for b in fresh.lengths for x in b]
            assert tree.n_tokens == fresh.n_tokens == len(bpe.encoding(bpe.vocabulary_path(VOCABULARY)).encode_ordinary(text))
            assert CountTree.unpacked(text, tree.packed(), counter).n_tokens == tree.n_tokens


def test_only_touched_regions_are_encoded_again():
    tree = CountTree.of("some words here " * 20_000, word_counter())
    tree.edit(100_000, 3, "new text")
    assert tree.re_encoded < 10


def test_whole_table(spark, sf):
    ranks = bpe.encoding(bpe.vocabulary_path(VOCABULARY))
    texts = {d.doc_id: d.text for d in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    rows = queries.op7_edit_aware_counts(spark, sf).collect()
    assert {r.doc_id for r in rows} == set(texts) and len(rows) == len(texts)
    for r in rows:
        assert r.n_tokens == len(ranks.encode_ordinary(texts[r.doc_id]))
        new = texts[r.doc_id]
        for e in r.edits:
            new = new[: e.start] + e.replacement + new[e.start + e.length :]
        assert r.n_tokens_after == len(ranks.encode_ordinary(new))


def test_hard_rows(spark):
    rows = [(1, None, [(0, 5, "x")]), (2, "", None), (2, "", []), (None, "abc", [(None, 1, "q"), (9, 9, None), (1, 1, None)])]
    df = spark.createDataFrame(rows, f"doc_id long, text string, edits {EDITS}")
    assert sorted(r.text for r in apply_edits(build_trees(df)).collect()) == ["", "", "ac", "x"]
    assert apply_edits(build_trees(df.where("false"))).count() == 0
    log = spark.createDataFrame([(1, 2, 0, 0, "b"), (1, 1, 0, 0, "a")], "doc_id long, seq int, start int, length int, replacement string")
    assert sorted(r.text for r in apply_edits(build_trees(attach_edits(df.select("doc_id", "text"), log))).collect()) == ["", "", "abc", "ba"]
