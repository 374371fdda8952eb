"""Pipelines that training corpora go through, each a variant to compare."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import canonical, sentences, tokens
from ..sources.tables import host_of, is_under
from . import fuzzy
from .audit import span_rows


def dedup_docs(docs: DataFrame, key: Column | None = None) -> DataFrame:
    """One document of each text, the one of least id. ``key`` may be a canonical
    form, which also joins texts that differ in white space, case or accents."""
    k = F.sha2(F.col("text") if key is None else key, 256)
    first = docs.groupBy(k.alias("_k")).agg(F.min("doc_id").alias("doc_id"))
    return docs.join(first.select("doc_id"), "doc_id", "left_semi")


def dedup_canonical(docs: DataFrame) -> DataFrame:
    return dedup_docs(docs, canonical(F.col("text")))


def dedup_spans(docs: DataFrame, n: int = 3) -> DataFrame:
    """(doc_id, text, kept, dropped): all but the first of each span of n sentences goes.

    The first is the one of least (id, position); its minimum is pre-aggregated,
    so a span that millions of documents hold costs one small row a task.
    """
    rows = span_rows(docs, n).select("doc_id", "pos", F.md5(F.col("span").cast("binary")).alias("span"))
    first = rows.groupBy("span").agg(F.min(F.struct("doc_id", "pos")).alias("first"), F.count(F.lit(1)).alias("m")).where("m > 1").select("span", F.col("first.doc_id").alias("d"), F.col("first.pos").alias("p"))
    again = rows.join(first, "span").where("doc_id != d or pos != p")
    gone = again.select("doc_id", F.explode(F.sequence(F.col("pos"), F.col("pos") + n - 1)).alias("pos")).groupBy("doc_id").agg(F.collect_set("pos").alias("gone"))
    s = sentences(F.col("text"))
    return _without(docs, gone, s, " ")


def dedup_paragraphs(docs: DataFrame) -> DataFrame:
    """(doc_id, text, kept, dropped): all but the first of each non-empty line goes."""
    lines = F.split(F.col("text"), "\n")
    rows = docs.select("doc_id", F.posexplode(lines).alias("pos", "line")).where("line != ''").select("doc_id", "pos", F.md5(F.col("line").cast("binary")).alias("line"))
    first = rows.groupBy("line").agg(F.min(F.struct("doc_id", "pos")).alias("first"), F.count(F.lit(1)).alias("m")).where("m > 1").select("line", F.col("first.doc_id").alias("d"), F.col("first.pos").alias("p"))
    gone = rows.join(first, "line").where("doc_id != d or pos != p").groupBy("doc_id").agg(F.collect_set("pos").alias("gone"))
    return _without(docs, gone, lines, "\n")


def _without(docs: DataFrame, gone: DataFrame, parts: Column, glue: str) -> DataFrame:
    met = docs.select("doc_id", parts.alias("_parts")).join(gone, "doc_id", "left")
    left = F.when(F.col("gone").isNull(), F.col("_parts")).otherwise(F.filter("_parts", lambda x, i: ~F.array_contains("gone", i)))
    return met.select("doc_id", F.array_join(left, glue).alias("text"), F.size(left).alias("kept"), (F.size("_parts") - F.size(left)).alias("dropped"))


def dedup_fuzzy(docs: DataFrame, jaccard: float = 0.8, bands: int = 24) -> DataFrame:
    """(doc_id, component): documents joined where the similarity of their shingles of five words is confirmed."""
    return fuzzy.components(docs, jaccard, bands)


def exclude_hosts(pages: DataFrame, suffixes: list[str], url: str = "url") -> DataFrame:
    return pages.where(~is_under(host_of(F.col(url)), suffixes))


def from_domain(pages: DataFrame, suffix: str, url: str = "url") -> DataFrame:
    return pages.where(is_under(host_of(F.col(url)), [suffix]))


#: Phrases of templates that stand in for text, and marks that prose doesn't hold.
BOILERPLATE = ["lorem ipsum", "terms of use", "cookie policy", "privacy policy", "javascript must be enabled", "all rights reserved", "404 not found"]
CODE = ["{", "};"]
#: Words that a filter may carry to every task.
MOST_WORDS = 10_000


def _letters(toks: Column) -> Column:
    return F.transform(toks, lambda w: F.regexp_replace(w, "[^a-z]", ""))


def content_filter(docs: DataFrame, words: list[str] | DataFrame, phrases: list[str] | None = None, code: list[str] | None = None) -> DataFrame:
    """Documents with ``reason``: unwanted word, boilerplate, code, or null where none holds.

    ``words``: a list, or a table (word) of at most MOST_WORDS rows, for example a
    file of a word a line or what ``unwanted_words`` learns.
    """
    hold = F.lit(False)
    for phrase in BOILERPLATE if phrases is None else phrases:
        hold = hold | F.col("_low").contains(phrase)
    marks = F.lit(False)
    for mark in CODE if code is None else code:
        marks = marks | F.col("text").contains(mark)
    if isinstance(words, DataFrame):
        if words.limit(MOST_WORDS + 1).count() > MOST_WORDS:
            raise ValueError(f"more than {MOST_WORDS} unwanted words")
        listed = docs.crossJoin(F.broadcast(words.agg(F.collect_set("word").alias("_words"))))  # one row
    else:
        listed = docs.withColumn("_words", F.array(*map(F.lit, words)).cast("array<string>"))
    unwanted = F.arrays_overlap(_letters(tokens(F.col("text"))), F.col("_words"))
    flagged = listed.withColumn("_low", F.lower("text")).withColumn("reason", F.when(unwanted, "words").when(hold, "boilerplate").when(marks, "code"))
    return flagged.drop("_low", "_words")


def unwanted_words(docs: DataFrame, labels: DataFrame, least: int = 3, times: int = 10) -> DataFrame:
    """(word): words of at least three letters that stand in ``least`` or more unwanted documents and in ``times`` as few wanted ones.

    ``labels``: (doc_id, toxic). Counted over all labelled documents, a document once for each word.
    """
    met = docs.join(labels.where("toxic is not null").select("doc_id", "toxic").distinct(), "doc_id")
    each = met.select("toxic", F.explode(F.array_distinct(_letters(tokens(F.col("text"))))).alias("word")).where(F.char_length("word") >= 3)
    counts = each.groupBy("word").agg(F.count_if(F.col("toxic") == 1).alias("bad"), F.count_if(F.col("toxic") == 0).alias("good"))
    return counts.where((F.col("bad") >= least) & (F.col("bad") >= times * F.col("good"))).select("word")


def upsample(docs: DataFrame, k: int) -> DataFrame:
    """A resource taken k times: a weight, not copies."""
    return docs.withColumn("weight", F.lit(k).cast("long"))


def mixture(parts: dict[str, DataFrame]) -> DataFrame:
    """Union of sub-corpora with their name as lineage; columns a part lacks are null."""
    return reduce(lambda x, y: x.unionByName(y, allowMissingColumns=True), [d.withColumn("subcorpus", F.lit(n)) for n, d in parts.items()])


def sample(docs: DataFrame, parts: int, of: int, id_col: str = "doc_id") -> DataFrame:
    """A public sample: the documents whose id's digest falls into the first ``parts`` of ``of`` classes."""
    return docs.where(F.pmod(F.conv(F.substring(F.md5(F.col(id_col).cast("string").cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(of)) < parts)


def chunks(docs: DataFrame, n: int, of: int, id_col: str = "doc_id") -> DataFrame:
    """n of so many random chunks of a crawl; a chunk is taken whole."""
    chunk = F.pmod(F.conv(F.substring(F.md5(F.col(id_col).cast("string").cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(of))
    return docs.withColumn("chunk", chunk).where(F.col("chunk") < n)


def first_of(docs: DataFrame, keys: list[str]) -> DataFrame:
    """The row of least id of each key, by a window: for small key groups."""
    return docs.withColumn("_r", F.row_number().over(Window.partitionBy(*keys).orderBy("doc_id"))).where("_r = 1").drop("_r")
