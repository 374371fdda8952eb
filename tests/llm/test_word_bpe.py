import hashlib

import pytest

from vintage.llm import bpe, queries
from vintage.llm.word_bpe import VOCABULARY, decode, decoded_digests, encode

HARD = [None, "", " ", "a", "it's don't  we'll\n\n x", "été ²³ ½ 12_34 __ \x1c\x1d z\x85 \xa0 end", "日本語 текст ١٢٣ \U0001f600 ok‍", "　 x   y", "a" * 30_000 + " " * 500, "tab\tx \r\n y"]


def expected(text):
    ids = bpe.encoding(bpe.vocabulary_path(VOCABULARY)).encode_ordinary(text or "")
    return len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((text or "").encode()).hexdigest()


def test_split_agrees_with_the_library_on_every_character():
    e = bpe.encoding(bpe.vocabulary_path(VOCABULARY))
    for start in range(0, 0x30000, 64):
        text = "".join(f"a{c}1{c} {c}{c}b  {c}" for c in map(chr, range(start, start + 64)) if not 0xD800 <= ord(c) < 0xE000)
        for t in (text, *(text[k : k + 12] for k in range(0, 60, 12))):
            words = bpe.split(t)
            assert "".join(words) == t
            assert [i for w in words for i in e.encode_ordinary(w)] == e.encode_ordinary(t)


def test_hard_texts(spark):
    rows = [(k, t, "x") for k, t in enumerate(HARD)] + [(3, HARD[3], "x"), (None, "no id", "x")]
    got = decoded_digests(encode(spark.createDataFrame(rows, "doc_id long, text string, ids string").repartition(3))).collect()
    want = sorted(((k, *expected(t)) for k, t, _ in rows), key=str)
    assert sorted((tuple(r) for r in got), key=str) == want


def test_empty_table(spark):
    assert decode(encode(spark.createDataFrame([], "doc_id long, text string"))).count() == 0


def test_whole_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").collect()
    got = {r.doc_id: (r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in queries.op3_word_bpe(spark, sf).collect()}
    assert got == {d.doc_id: expected(d.text) for d in docs}


@pytest.mark.parametrize("ids,want", [([], b""), (None, b""), ([999_999, -5], b"")])
def test_unknown_ids(spark, ids, want):
    df = spark.createDataFrame([(1, ids)], "doc_id long, ids array<int>")
    assert bytes(decode(df).first().decoded) == want
