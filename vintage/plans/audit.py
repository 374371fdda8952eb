"""Why cutoffs and dates differ: leftover copies, twins, old content in new dumps."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import joined_runs, sentences, shingles
from ..sources.tables import stored
from . import mining


def share_older(hist: DataFrame, dump_month: int, by: list[str] | None = None) -> DataFrame:
    """Share of matched documents whose version is older than the dump."""
    total = F.nullif(F.sum("n"), F.lit(0.0))
    old = F.sum(F.when(F.col("month_ix") < dump_month, F.col("n")).otherwise(0.0))
    return hist.groupBy(*(by or [])).agg(F.sum("n").alias("matched"), (old / total).alias("share_older"))


def dump_age(attributed: DataFrame) -> DataFrame:
    """For each dump (subcorpus, dump_month): median age in months, share older, mean minus median."""
    age = F.col("dump_month") - F.col("month_ix")
    return attributed.groupBy("subcorpus", "dump_month").agg(F.count(F.lit(1)).alias("n"), F.percentile(age, F.lit(0.5)).alias("median_age"), F.avg((age > 0).cast("double")).alias("share_old"), (F.avg(age) - F.percentile(age, F.lit(0.5))).alias("skew"))


def copies_versions(attributed: DataFrame, corpus: DataFrame) -> DataFrame:
    """For each topic: matched documents, exact copies among them, distinct versions."""
    docs = attributed.select("topic_id", "doc_id").distinct().join(corpus.select("doc_id", F.sha2("text", 256).alias("h")), "doc_id")
    per = docs.groupBy("topic_id").agg(F.count(F.lit(1)).alias("documents"), F.countDistinct("h").alias("texts"))
    return per.select("topic_id", "documents", (F.col("documents") - F.col("texts")).alias("copies"), F.col("texts").alias("versions"))


def twins(corpus: DataFrame, ignore: str = "space", text: str = "text") -> DataFrame:
    """Groups of different texts that are one but for white space (``space``) or digits (``digits``): (key, texts, documents)."""
    c = F.col(text)
    key = F.regexp_replace(c, r"\s+", "") if ignore == "space" else F.regexp_replace(c, r"[0-9]+", "#")
    return corpus.groupBy(F.md5(key.cast("binary")).alias("key")).agg(F.countDistinct(F.md5(c.cast("binary"))).alias("texts"), F.count(F.lit(1)).alias("documents")).where("texts > 1")


def span_rows(corpus: DataFrame, n: int = 3, text: str = "text") -> DataFrame:
    """(doc_id, pos, span): every run of n sentences of a text."""
    return corpus.select("doc_id", F.posexplode(joined_runs(sentences(F.col(text)), n)).alias("pos", "span"))


def spans(corpus: DataFrame, n: int = 3) -> DataFrame:
    """Spans that stand more than once: (span digest, occurrences, documents)."""
    rows = span_rows(corpus, n).select("doc_id", F.md5(F.col("span").cast("binary")).alias("span"))
    return rows.groupBy("span").agg(F.count(F.lit(1)).alias("occurrences"), F.countDistinct("doc_id").alias("documents")).where("occurrences > 1")


def paragraphs(corpus: DataFrame) -> DataFrame:
    """Non-empty lines that stand more than once: (line digest, occurrences, documents)."""
    rows = corpus.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where("line != ''")
    return rows.groupBy(F.md5(F.col("line").cast("binary")).alias("line")).agg(F.count(F.lit(1)).alias("occurrences"), F.countDistinct("doc_id").alias("documents")).where("occurrences > 1")


def exact_groups(corpus: DataFrame) -> DataFrame:
    """Texts that several documents share: (text digest, documents, least id)."""
    return corpus.groupBy(F.md5(F.col("text").cast("binary")).alias("digest")).agg(F.count(F.lit(1)).alias("documents"), F.min("doc_id").alias("first")).where("documents > 1")


def leak_through(pages: DataFrame, excluded: Column, probes: DataFrame, n: int = 8) -> DataFrame:
    """Pages outside an excluded domain that hold a run of n words of its pages: (page_id, runs, sources, weight).

    ``pages``: (page_id, host, toks); ``probes``: (page_id, toks) of the domain,
    where equal texts count as one source. No run is left out: ``runs`` counts
    those a page shares with the domain, ``sources`` the texts it shares one with,
    and ``weight`` adds one over the number of sources for each run, so that runs
    common to many pages say little. Runs that stand on the same sources, and pages
    that meet the same such sets, are each resolved to sources once.
    """
    def runs(df: DataFrame, name: str) -> DataFrame:
        return df.select(F.col("page_id").alias(name), F.explode(shingles(F.col("toks"), n)).alias("run"))

    def digest(ids: Column) -> Column:
        return F.sha2(F.array_join(ids.cast("array<string>"), ","), 256)

    texts = probes.groupBy(F.sha2(F.array_join("toks", " "), 256)).agg(F.min("page_id").alias("page_id"), F.first("toks").alias("toks"))
    own = stored(runs(texts, "source").groupBy("run").agg(F.array_sort(F.collect_list("source")).alias("ids")).withColumn("set", digest(F.col("ids"))))
    sets = own.groupBy("set").agg(F.first("ids").alias("ids"))
    met = runs(pages.where(~excluded), "page_id").join(own.select("run", "set", F.size("ids").alias("m")), "run")
    per = met.groupBy("page_id").agg(F.count(F.lit(1)).alias("runs"), F.sum(1 / F.col("m")).alias("weight"), F.array_sort(F.collect_set("set")).alias("met"))
    per = stored(per.withColumn("mix", digest(F.col("met"))))
    mixes = per.groupBy("mix").agg(F.first("met").alias("met")).select("mix", F.explode("met").alias("set"))
    sources = mixes.join(sets, "set").select("mix", F.explode("ids").alias("source")).groupBy("mix").agg(F.countDistinct("source").alias("sources"))
    return per.join(sources, "mix").select("page_id", "runs", "sources", F.round("weight", 6).alias("weight"))


def leak_matches(pages: DataFrame, excluded: Column, threshold: float = 0.2, k: int = 10, n_words: int = 512) -> DataFrame:
    """Pages outside an excluded domain that are near copies of one of its pages: (source, page_id, dist, norm).

    Retrieval and edit distance, as for dated versions: each distinct page of the
    domain is a topic with one version, and the rest of the pages the corpus.
    """
    own = pages.where(excluded).groupBy("toks").agg(F.min("page_id").alias("topic_id"))
    none = F.array().cast("array<struct<month:int,pos:int,token:string>>")
    packed = stored(own.select("topic_id", "toks", F.lit("").alias("tail"), none.alias("edits")))
    corpus = pages.where(~excluded).select(F.col("page_id").alias("doc_id"), "toks", F.array_join("toks", " ").alias("text"))
    hits = mining.top_k_scan(corpus, mining.query_terms(packed, n_words), k)
    matched = mining.edit_match(mining.compare_versions(hits, corpus, packed, threshold))
    return matched.select(F.col("topic_id").alias("source"), F.col("doc_id").alias("page_id"), "dist", "norm")
