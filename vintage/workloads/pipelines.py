"""Workloads on corpora: dedup pipelines, filters, mixtures, and what they leave behind."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import tokens
from ..plans import audit, corpora
from ..sources.tables import host_of, is_under, stored, table, text_of_html
from . import setup as s

#: Fixed list: English words that the content filter doesn't want.
UNWANTED = ["clown", "disgusting", "idiot", "loser", "moron", "pathetic", "scum", "stupid", "trash", "worthless"]
EXCLUDED = ["example.org"]


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents", "doc_id", "text")


def dedup_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpora.dedup_docs(_docs(spark, sf_dir)).select("doc_id")


def dedup_canonical(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The remedy: texts that differ in white space, case or accents are one."""
    return corpora.dedup_canonical(_docs(spark, sf_dir)).select("doc_id")


def dedup_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = corpora.dedup_spans(_docs(spark, sf_dir))
    return out.select("doc_id", F.md5(F.col("text").cast("binary")).alias("digest"), "kept", "dropped")


def dedup_paras(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = corpora.dedup_paragraphs(_docs(spark, sf_dir))
    return out.select("doc_id", F.md5(F.col("text").cast("binary")).alias("digest"), "kept", "dropped")


def dedup_fuzzy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpora.dedup_fuzzy(_docs(spark, sf_dir))


def exclude_hosts(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages", "page_id", "url")
    return corpora.exclude_hosts(pages, EXCLUDED).select("page_id", host_of(F.col("url")).alias("host"))


def from_domain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpora.from_domain(table(spark, sf_dir, "pages", "page_id", "url"), "example.net").select("page_id")


def _reasons(flagged: DataFrame, spark: SparkSession, sf_dir: str) -> DataFrame:
    named = flagged.select("doc_id", F.coalesce("reason", F.lit("kept")).alias("reason"))
    met = named.join(table(spark, sf_dir, "labels", "doc_id", "quality", "toxic"), "doc_id", "left")
    return met.groupBy("reason", F.col("toxic").cast("double").alias("toxic")).agg(F.count(F.lit(1)).alias("documents"))


def content_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the content filter drops by a fixed list of words, beside the labels."""
    return _reasons(corpora.content_filter(_docs(spark, sf_dir), UNWANTED), spark, sf_dir)


def content_filter_learned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by words learned from the labelled documents, in whatever language they are."""
    docs = _docs(spark, sf_dir)
    words = stored(corpora.unwanted_words(docs, table(spark, sf_dir, "labels", "doc_id", "toxic")))
    return _reasons(corpora.content_filter(docs, words), spark, sf_dir)


def mixture_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A mixture of sources, pages and an up-sampled resource: documents, words and weighted words by part."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "source")
    parts = {
        "crawl": docs.where("source != 'src0'").withColumn("weight", F.lit(1).cast("long")),
        "dump": corpora.upsample(docs.where("source = 'src0'"), 3),
        "static": table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("doc_id"), "text").withColumn("weight", F.lit(1).cast("long")),
    }
    mixed = corpora.mixture(parts).withColumn("words", F.size(tokens(F.col("text"))).cast("long"))
    return mixed.groupBy("subcorpus").agg(F.count(F.lit(1)).alias("documents"), F.sum("words").alias("words"), F.sum(F.col("words") * F.col("weight")).alias("weighted"))


def public_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpora.sample(_docs(spark, sf_dir), 12, 100).select("doc_id")


def crawl_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpora.chunks(_docs(spark, sf_dir), 22, 367).groupBy("chunk").agg(F.count(F.lit(1)).alias("documents"))


def _with_twins(spark, sf_dir):
    """Documents, and for some of them a twin that differs in white space or digits only."""
    docs = _docs(spark, sf_dir)
    spaced = docs.where("doc_id % 50 = 0").select((F.col("doc_id") + 20_000_000).alias("doc_id"), F.replace("text", F.lit(" "), F.lit("  ")).alias("text"))
    cited = docs.where("doc_id % 50 = 1")
    cited = [cited.select((F.col("doc_id") + 30_000_000 + k * 10_000_000).alias("doc_id"), F.concat("text", F.lit(" ["), (F.col("doc_id") % 9 + k).cast("string"), F.lit("]")).alias("text")) for k in (0, 1)]
    return docs.union(spaced).union(cited[0]).union(cited[1])


def twins_space(spark: SparkSession, sf_dir: str) -> DataFrame:
    return audit.twins(_with_twins(spark, sf_dir), "space")


def twins_digits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return audit.twins(_with_twins(spark, sf_dir), "digits")


def span3_survivors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spans of three sentences that document-level dedup leaves standing more than once."""
    return audit.spans(corpora.dedup_docs(_docs(spark, sf_dir)))


def para_survivors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return audit.paragraphs(corpora.dedup_docs(_docs(spark, sf_dir)))


def exact_survivors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact duplicates that paragraph-level dedup turns up or leaves, empty texts aside."""
    out = corpora.dedup_paragraphs(_docs(spark, sf_dir))
    return audit.exact_groups(out.where("text != ''").select("doc_id", "text"))


def corpus_volume(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents, words and bytes of a corpus, by source."""
    docs = table(spark, sf_dir, "documents", "source", "text")
    return docs.groupBy("source").agg(F.count(F.lit(1)).alias("documents"), F.sum(F.size(tokens(F.col("text")))).alias("words"), F.sum(F.octet_length("text")).alias("bytes"))


def domain_leak(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages outside an excluded domain that hold its content."""
    pages = table(spark, sf_dir, "pages").select("page_id", host_of(F.col("url")).alias("host"), tokens(text_of_html(F.col("html"))).alias("toks"))
    inside = is_under(F.col("host"), EXCLUDED)
    return audit.leak_through(pages, inside, pages.where(inside))


def domain_leak_matches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages outside an excluded domain within a fifth of their length of one of its pages."""
    pages = table(spark, sf_dir, "pages").select("page_id", host_of(F.col("url")).alias("host"), tokens(text_of_html(F.col("html"))).alias("toks"))
    out = audit.leak_matches(pages, is_under(F.col("host"), EXCLUDED))
    return out.select("source", "page_id", "dist", F.round("norm", 6).alias("norm"))


def pages_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages", "page_id", "html").select("page_id", text_of_html(F.col("html")).alias("text"))
    return pages.select("page_id", F.char_length("text").alias("chars"), F.md5(F.col("text").cast("binary")).alias("digest"))


def page_hosts(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages", "url").select(host_of(F.col("url")).alias("host"))
    return pages.groupBy("host").agg(F.count(F.lit(1)).alias("pages"))


QUERIES = {f.__name__: f for f in (dedup_docs, dedup_canonical, dedup_spans, dedup_paras, dedup_fuzzy, exclude_hosts, from_domain, content_filter, content_filter_learned, mixture_stats, public_sample, crawl_chunks, twins_space, twins_digits, span3_survivors, para_survivors, exact_survivors, corpus_volume, domain_leak, domain_leak_matches, pages_text, page_hosts)}

# --- SQL -------------------------------------------------------------------

_HOST = "lower(regexp_extract(url, '://([^/?#:]+)', 1))"
_UNDER = lambda d: f"({_HOST} = '{d}' OR {_HOST} LIKE '%.{d}')"
_SENT = r"string_split(regexp_replace({0}, '([.!?])\s+', '\1' || chr(1), 'g'), chr(1))"
_TOKS = s.sql_tokens
_FIRST = "firsts AS (SELECT min(doc_id) AS doc_id FROM documents GROUP BY text), kept_docs AS (SELECT doc_id, text FROM documents JOIN firsts USING (doc_id))"
_SPANS = lambda src: f"parts AS (SELECT doc_id, {_SENT.format('text')} AS p FROM {src}), spans AS (SELECT doc_id, pos, array_to_string(p[pos + 1:pos + 3], ' ') AS span FROM (SELECT doc_id, p, unnest(range(0, len(p) - 2)) AS pos FROM parts))"
_LINES = "parts AS (SELECT doc_id, string_split(text, chr(10)) AS p FROM documents), lines AS (SELECT doc_id, generate_subscripts(p, 1) - 1 AS pos, unnest(p) AS span FROM parts)"
_AGAIN = lambda src, n, glue: f"again AS (SELECT doc_id, pos FROM (SELECT *, row_number() OVER (PARTITION BY span ORDER BY doc_id, pos) AS r FROM {src}) WHERE r > 1), gone AS (SELECT DISTINCT doc_id, unnest(range(pos, pos + {n})) AS pos FROM again), left_parts AS (SELECT d.doc_id, d.pos, d.part, g.pos IS NOT NULL AS cut FROM (SELECT doc_id, generate_subscripts(p, 1) - 1 AS pos, unnest(p) AS part FROM parts) d LEFT JOIN gone g ON g.doc_id = d.doc_id AND g.pos = d.pos), left_texts AS (SELECT doc_id, coalesce(string_agg(CASE WHEN NOT cut THEN part END, {glue} ORDER BY pos), '') AS text, CAST(count(*) FILTER (NOT cut) AS INTEGER) AS kept, CAST(count(*) FILTER (cut) AS INTEGER) AS dropped FROM left_parts GROUP BY 1)"
_PARAS = f"{_LINES}, full_lines AS (SELECT * FROM lines WHERE span != ''), {_AGAIN('full_lines', 1, 'chr(10)')}"
_TWINS = "docs AS (SELECT doc_id, text FROM documents UNION ALL SELECT doc_id, replace(text, ' ', '  ') FROM documents WHERE doc_id % 50 = 0 UNION ALL SELECT doc_id, text || ' [' || (doc_id % 9) || ']' FROM documents WHERE doc_id % 50 = 1 UNION ALL SELECT doc_id, text || ' [' || (doc_id % 9 + 1) || ']' FROM documents WHERE doc_id % 50 = 1)"
_TWIN = lambda pat, rep: rf"WITH {_TWINS} SELECT md5(regexp_replace(text, '{pat}', '{rep}', 'g')) AS key, count(DISTINCT md5(text)) AS texts, count(*) AS documents FROM docs GROUP BY 1 HAVING count(DISTINCT md5(text)) > 1"
_CLASS = lambda n: f"CAST(('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 8)) AS BIGINT) % {n}"


def _page_text() -> str:
    out = r"regexp_replace(html, '(?is)<script[^>]*>.*?</script>|<style[^>]*>.*?</style>|<!--.*?-->', ' ', 'g')"
    out = rf"regexp_replace(regexp_replace({out}, '(?i)<br>|</p>|</h1>|</li>', chr(10), 'g'), '<[^>]*>', ' ', 'g')"
    for name, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&copy;", "©"), ("&middot;", "·"), ("&nbsp;", " "), ("&amp;", "&")):
        out = f"replace({out}, '{name}', '{char}')"
    return rf"trim(regexp_replace(regexp_replace({out}, '[ \t]+', ' ', 'g'), ' ?\n[ \n]*', chr(10), 'g'))"


_RUNS = "list_distinct(list_transform(range(1, len(toks) - 6), lambda i: array_to_string(toks[i:i + 7], ' ')))"
_FUZZY = f"""WITH RECURSIVE docs AS (SELECT doc_id, {_TOKS('text')} AS w FROM documents), texts AS (SELECT min(doc_id) AS rep, w FROM docs GROUP BY w),
 grams AS (SELECT rep, unnest(CASE WHEN len(w) >= 5 THEN list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) ELSE [array_to_string(w, ' ')] END) AS g FROM texts WHERE len(w) > 0), sizes AS (SELECT rep, count(*) AS n FROM grams GROUP BY 1),
 pairs AS (SELECT x.rep AS a, y.rep AS b, count(*) AS i FROM grams x JOIN grams y ON x.g = y.g AND x.rep < y.rep GROUP BY 1, 2), links AS (SELECT a, b FROM pairs JOIN sizes p ON p.rep = a JOIN sizes q ON q.rep = b WHERE 100 * i >= 80 * (p.n + q.n - i)),
 sides AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links), reach(a, b) AS (SELECT a, b FROM sides UNION SELECT r.a, e.b FROM reach r JOIN sides e ON e.a = r.b), least AS (SELECT a, least(a, min(b)) AS c FROM reach GROUP BY a)
 SELECT doc_id, CASE WHEN len(w) = 0 THEN doc_id ELSE coalesce(c, rep) END AS component FROM docs JOIN texts USING (w) LEFT JOIN least ON least.a = rep"""
_WORDS = ", ".join(f"'{w}'" for w in UNWANTED)
_PHRASES = " OR ".join(f"contains(lower(text), '{p}')" for p in corpora.BOILERPLATE)
_MARKS = " OR ".join(f"contains(text, '{m}')" for m in corpora.CODE)


def _filter_sql(words: str, before: str = "") -> str:
    letters = f"list_transform({_TOKS('text')}, lambda w: regexp_replace(w, '[^a-z]', '', 'g'))"
    return f"WITH {before} flagged AS (SELECT doc_id, CASE WHEN list_has_any({letters}, {words}) THEN 'words' WHEN {_PHRASES} THEN 'boilerplate' WHEN {_MARKS} THEN 'code' ELSE 'kept' END AS reason FROM documents) SELECT reason, CAST(toxic AS DOUBLE) AS toxic, count(*) AS documents FROM flagged LEFT JOIN labels USING (doc_id) GROUP BY 1, 2"


ORACLE_SQL = {
    "dedup_docs": "SELECT min(doc_id) AS doc_id FROM documents GROUP BY text",
    "dedup_canonical": f"SELECT min(doc_id) AS doc_id FROM documents GROUP BY {s.sql_canonical('text')}",
    "dedup_spans": f"WITH {_SPANS('documents')}, {_AGAIN('spans', 3, chr(39) + ' ' + chr(39))} SELECT doc_id, md5(text) AS digest, kept, dropped FROM left_texts",
    "dedup_paras": f"WITH {_PARAS} SELECT doc_id, md5(text) AS digest, kept, dropped FROM left_texts",
    "dedup_fuzzy": _FUZZY,
    "exclude_hosts": f"SELECT page_id, {_HOST} AS host FROM pages WHERE NOT {_UNDER('example.org')}",
    "from_domain": f"SELECT page_id FROM pages WHERE {_UNDER('example.net')}",
    "content_filter": _filter_sql(f"[{_WORDS}]"),
    "content_filter_learned": _filter_sql("(SELECT list(word) FROM learned)", f"labelled AS (SELECT doc_id, toxic, {_TOKS('text')} AS toks FROM documents JOIN (SELECT DISTINCT doc_id, toxic FROM labels WHERE toxic IS NOT NULL) USING (doc_id)), seen AS (SELECT DISTINCT doc_id, toxic, regexp_replace(unnest(toks), '[^a-z]', '', 'g') AS word FROM labelled), learned AS (SELECT word FROM seen WHERE length(word) >= 3 GROUP BY 1 HAVING count(*) FILTER (toxic = 1) >= 3 AND count(*) FILTER (toxic = 1) >= 10 * count(*) FILTER (toxic = 0)),"),
    "mixture_stats": f"WITH m AS (SELECT CASE WHEN source = 'src0' THEN 'dump' ELSE 'crawl' END AS subcorpus, CASE WHEN source = 'src0' THEN 3 ELSE 1 END AS weight, {_TOKS('text')} AS toks FROM documents UNION ALL SELECT 'static', 1, {_TOKS('text')} FROM benchmark) SELECT subcorpus, count(*) AS documents, CAST(sum(len(toks)) AS BIGINT) AS words, CAST(sum(len(toks) * weight) AS BIGINT) AS weighted FROM m GROUP BY 1",
    "public_sample": f"SELECT doc_id FROM documents WHERE {_CLASS(100)} < 12",
    "crawl_chunks": f"SELECT {_CLASS(367)} AS chunk, count(*) AS documents FROM documents WHERE {_CLASS(367)} < 22 GROUP BY 1",
    "twins_space": _TWIN(r"\s+", ""),
    "twins_digits": _TWIN("[0-9]+", "#"),
    "span3_survivors": f"WITH {_FIRST}, {_SPANS('kept_docs')} SELECT md5(span) AS span, count(*) AS occurrences, count(DISTINCT doc_id) AS documents FROM spans GROUP BY 1 HAVING count(*) > 1",
    "para_survivors": f"WITH {_FIRST}, lines AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM kept_docs) SELECT md5(line) AS line, count(*) AS occurrences, count(DISTINCT doc_id) AS documents FROM lines WHERE line != '' GROUP BY 1 HAVING count(*) > 1",
    "exact_survivors": f"WITH {_PARAS} SELECT md5(text) AS digest, count(*) AS documents, min(doc_id) AS first FROM left_texts WHERE text != '' GROUP BY 1 HAVING count(*) > 1",
    "corpus_volume": f"SELECT source, count(*) AS documents, CAST(sum(len({_TOKS('text')})) AS BIGINT) AS words, CAST(sum(octet_length(encode(text))) AS BIGINT) AS bytes FROM documents GROUP BY 1",
    "domain_leak": f"WITH p AS (SELECT page_id, {_UNDER('example.org')} AS inside, {_TOKS(_page_text())} AS toks FROM pages), texts AS (SELECT min(page_id) AS source, toks FROM p WHERE inside GROUP BY toks), own AS (SELECT source, unnest({_RUNS}) AS run FROM texts), runs AS (SELECT page_id, unnest({_RUNS}) AS run FROM p WHERE NOT inside), per AS (SELECT run, count(*) AS m FROM own GROUP BY 1), weights AS (SELECT page_id, count(*) AS runs, round(sum(1.0 / m::DOUBLE), 6) AS weight FROM runs JOIN per USING (run) GROUP BY 1), met AS (SELECT page_id, count(DISTINCT source) AS sources FROM runs JOIN own USING (run) GROUP BY 1) SELECT page_id, runs, sources, weight FROM weights JOIN met USING (page_id)",
    "pages_text": f"SELECT page_id, CAST(length(text) AS INTEGER) AS chars, md5(text) AS digest FROM (SELECT page_id, {_page_text()} AS text FROM pages)",
    "page_hosts": f"SELECT {_HOST} AS host, count(*) AS pages FROM pages GROUP BY 1",
}
