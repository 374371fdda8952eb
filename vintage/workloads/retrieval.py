"""Workloads on the corpus side: retrieval, confirmation, attribution, histograms."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import tokens
from ..functions.timegrid import months
from ..plans import audit, compare, curves, mining, probes
from ..sources.tables import stored, table
from . import setup as s

#: The mix whose versions are planted, and its direct dump.
MIX, DUMP = "multidump_mid", 72
#: Planted ids: OFFSET + topic * 100 + month. Months below DUMP came by crawls, two to a dump.
OFFSET, CRAWLS = 10_000_000, {16: 40, 24: 40, 28: 75}


def _topics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every topic with its whole history in a row."""
    packed = probes.packed_set(table(spark, sf_dir, "documents", "doc_id", "text"), s.edits(spark, sf_dir), s.chosen_topics(spark, sf_dir), s.TOPIC_TOKENS)
    return stored(packed.repartition(2 * spark.sparkContext.defaultParallelism, "topic_id"))  # few rows, much work on each


def _corpus(spark: SparkSession, sf_dir: str, packed: DataFrame) -> DataFrame:
    """Whole documents and whole planted versions (doc_id, subcorpus, version_month, toks, text)."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    plain = docs.select("doc_id", F.lit("background").alias("subcorpus"), F.lit(None).cast("int").alias("version_month"), tokens(F.col("text")).alias("toks"))
    at = packed.withColumn("month_ix", F.explode(F.array(*map(F.lit, sorted(s.MIXES[MIX])))))
    name = F.when(F.col("month_ix") == DUMP, "direct").otherwise(F.concat(F.lit("crawl"), F.when(F.col("month_ix") <= 24, "40").otherwise("75")))
    planted = at.select((F.lit(OFFSET) + F.col("topic_id") * 100 + F.col("month_ix")).alias("doc_id"), name.alias("subcorpus"), F.col("month_ix").alias("version_month"), F.split(probes.text_at(F.col("month_ix")), " ").alias("toks"))
    return plain.union(planted).withColumn("text", F.array_join("toks", " "))


def _queries(packed: DataFrame) -> DataFrame:
    return mining.query_terms(packed.select("topic_id", probes.words_at(F.lit(DUMP)).alias("toks")))


def bm25_top10(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten best documents for each topic by an index."""
    packed = _topics(spark, sf_dir)
    return mining.top_k(mining.build_index(_corpus(spark, sf_dir, packed)), _queries(packed))


def bm25_top10_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by one scan of the corpus, without an index."""
    packed = _topics(spark, sf_dir)
    return mining.top_k_scan(_corpus(spark, sf_dir, packed), _queries(packed))


def _hits(spark, sf_dir):
    """Ten documents for each topic, the corpus they are from, and the topics."""
    packed = _topics(spark, sf_dir)
    corpus = _corpus(spark, sf_dir, packed)
    return stored(mining.top_k_scan(corpus, _queries(packed))), corpus, packed


def _compared(spark, sf_dir):
    hits, corpus, packed = _hits(spark, sf_dir)
    return stored(mining.compare_versions(hits, corpus, packed)), hits, corpus, packed


def _matched_by_edits(spark, sf_dir):
    compared, _, corpus, _ = _compared(spark, sf_dir)
    return mining.edit_match(compared), corpus


def _matched_by_ngrams(spark, sf_dir):
    hits, corpus, packed = _hits(spark, sf_dir)
    return stored(mining.ngram_match(hits, corpus, probes.whole_versions(packed))), corpus


def _placed(matched_and_corpus, ties="all"):
    """Attributed matches with the part of the corpus they are from, and the corpus."""
    matched, corpus = matched_and_corpus
    return mining.attribute(matched, ties).join(corpus.select("doc_id", "subcorpus"), "doc_id"), corpus


def edit_matches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hits within a fifth of their length of some version, with distance."""
    matched, _ = _matched_by_edits(spark, sf_dir)
    return matched.select("topic_id", "doc_id", "version_from", "version_to", "dist", F.round("norm", 6).alias("norm"))


def mining_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What mining costs: hits, pairs of a hit and a version, pairs that lengths rule out, distances taken, matches."""
    return mining.costs(_compared(spark, sf_dir)[0])


def version_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Matched documents a month, by edit distance, ties counted for every nearest month."""
    return mining.histogram(mining.attribute(_matched_by_edits(spark, sf_dir)[0]), months(spark))


def attribution_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edit distance and shared n-grams attribute nearly every document alike."""
    compared, hits, corpus, packed = _compared(spark, sf_dir)
    by_edit = mining.month_sets(mining.attribute(mining.edit_match(compared)))
    by_ngram = mining.month_sets(mining.attribute(stored(mining.ngram_match(hits, corpus, probes.whole_versions(packed)))))
    return compare.agreement(by_edit, by_ngram)


def _by_subcorpus(placed, spark):
    return mining.histogram(placed[0], months(spark), ["subcorpus"])


def _share_older(placed, spark):
    hist = mining.histogram(placed[0], months(spark))
    return audit.share_older(hist, DUMP).select("matched", F.round("share_older", 4).alias("share_older"))


def _curve_corr(placed, spark, sf_dir):
    curve = curves.relative(curves.trimmed_mean(s.topic_perplexity(spark, sf_dir, [MIX])))
    hist = mining.histogram(placed[0], months(spark)).withColumn("model", F.lit(MIX))
    return compare.curve_vs_hist(curve, hist).select("model", F.round("pearson", 4).alias("pearson"), F.round("spearman", 4).alias("spearman"))


def _ages(placed):
    aged = placed[0].where("subcorpus like 'crawl%'").withColumn("dump_month", F.regexp_extract("subcorpus", "([0-9]+)", 1).cast("int"))
    out = audit.dump_age(aged)
    return out.select("subcorpus", "dump_month", "n", "median_age", F.round("share_old", 4).alias("share_old"), F.round("skew", 4).alias("skew"))


def histogram_by_subcorpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Versions by month, stacked by the part of the training set they came from."""
    return _by_subcorpus(_placed(_matched_by_edits(spark, sf_dir)), spark)


def share_older_than_dump(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of matched documents older than the direct dump."""
    return _share_older(_placed(_matched_by_edits(spark, sf_dir), "latest"), spark)


def curve_hist_corr(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Relative perplexity falls where the corpus holds many versions."""
    return _curve_corr(_placed(_matched_by_edits(spark, sf_dir)), spark, sf_dir)


def dump_age(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How old the versions inside each crawl dump are against its date."""
    return _ages(_placed(_matched_by_edits(spark, sf_dir), "latest"))


def copies_vs_versions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact copies and distinct versions among each topic's matches."""
    return audit.copies_versions(*_placed(_matched_by_edits(spark, sf_dir)))


def ngram_matches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The footnote's check: hits by shared five-word runs."""
    matched, _ = _matched_by_ngrams(spark, sf_dir)
    return matched.select("topic_id", "doc_id", "version_from", "version_to", F.round("share", 6).alias("share"))


def ngram_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mining.histogram(mining.attribute(_matched_by_ngrams(spark, sf_dir)[0]), months(spark))


def ngram_histogram_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each document counts once, shared among its nearest months."""
    return mining.histogram(mining.attribute(_matched_by_ngrams(spark, sf_dir)[0], "split"), months(spark)).select("month_ix", F.round("n", 4).alias("n"))


def ngram_by_subcorpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _by_subcorpus(_placed(_matched_by_ngrams(spark, sf_dir)), spark)


def ngram_share_older(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _share_older(_placed(_matched_by_ngrams(spark, sf_dir), "latest"), spark)


def ngram_curve_corr(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _curve_corr(_placed(_matched_by_ngrams(spark, sf_dir)), spark, sf_dir)


def ngram_dump_age(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _ages(_placed(_matched_by_ngrams(spark, sf_dir), "latest"))


def ngram_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    return audit.copies_versions(*_placed(_matched_by_ngrams(spark, sf_dir)))


def static_inclusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Membership-style baseline: it says that versions are in, not when they stopped coming."""
    ppl = s.topic_perplexity(spark, sf_dir, [MIX, "webonly"])
    return mining.static_inclusion(ppl, 100.0)


def exact_inclusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    packed = _topics(spark, sf_dir)
    return mining.exact_inclusion(probes.whole_versions(packed), _corpus(spark, sf_dir, packed)).select("topic_id", "version_from", "version_to")


QUERIES = {f.__name__: f for f in (bm25_top10, bm25_top10_scan, edit_matches, mining_costs, version_histogram, attribution_agreement, histogram_by_subcorpus, share_older_than_dump, curve_hist_corr, dump_age, copies_vs_versions, ngram_matches, ngram_histogram, ngram_histogram_split, ngram_by_subcorpus, ngram_share_older, ngram_curve_corr, ngram_dump_age, ngram_copies, static_inclusion, exact_inclusion)}

# --- SQL -------------------------------------------------------------------

_AT = sorted(s.MIXES[MIX])
_CORPUS = f"""tails AS (SELECT topic_id, w.toks[{s.TOPIC_TOKENS + 1}:] AS tail FROM topics JOIN words w ON w.doc_id = topic_id),
heads AS (SELECT topic_id, m, list(token ORDER BY pos) AS head FROM ints JOIN (SELECT unnest({_AT}) AS m) ON f <= m AND m <= t GROUP BY 1, 2), planted AS (SELECT topic_id, m, head, head || tail AS toks FROM heads JOIN tails USING (topic_id)),
corpus AS (SELECT doc_id, 'background' AS subcorpus, toks FROM words UNION ALL SELECT {OFFSET} + topic_id * 100 + m, CASE WHEN m = {DUMP} THEN 'direct' WHEN m <= 24 THEN 'crawl40' ELSE 'crawl75' END, toks FROM planted),
asked AS (SELECT topic_id, term, count(*) AS qtf FROM (SELECT topic_id, unnest(head) AS term FROM planted WHERE m = {DUMP}) GROUP BY 1, 2),
tf AS (SELECT doc_id, term, count(*) AS tf FROM (SELECT doc_id, unnest(toks) AS term FROM corpus) GROUP BY 1, 2), df AS (SELECT term, count(*) AS df FROM tf GROUP BY 1), lens AS (SELECT doc_id, len(toks) AS length FROM corpus),
totals AS (SELECT count(*) AS docs, avg(length) AS mean_length FROM lens),
scores AS (SELECT topic_id, doc_id, round(sum(qtf * ln(1 + (docs - df + 0.5) / (df + 0.5)) * tf * {mining.K1 + 1} / (tf + {mining.K1} * (1 - {mining.B} + {mining.B} * length / mean_length))), 6) AS score FROM tf JOIN asked USING (term) JOIN df USING (term) JOIN lens USING (doc_id), totals GROUP BY 1, 2),
best AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY topic_id ORDER BY score DESC, doc_id) AS rank FROM scores) WHERE rank <= 10)"""
_BASE = f"WITH {s.sql_topics()}, {_CORPUS}"
_VTEXT = "vtext AS (SELECT topic_id, vf, vt, head || tail AS toks FROM (SELECT topic_id, vf, vt, list(token ORDER BY pos) AS head FROM vtok GROUP BY 1, 2, 3) JOIN tails USING (topic_id))"
_GRAMS = "SELECT DISTINCT {0}, g FROM (SELECT *, concat_ws(' ', w, lead(w) OVER x, lead(w, 2) OVER x, lead(w, 3) OVER x, lead(w, 4) OVER x) AS g, lead(w, 4) OVER x AS fifth FROM (SELECT {0}, generate_subscripts(toks, 1) AS pos, unnest(toks) AS w FROM {1}) WINDOW x AS (PARTITION BY {0} ORDER BY pos)) WHERE fifth IS NOT NULL"
_NGRAM = f"""{_BASE}, {_VTEXT}, vgram AS ({_GRAMS.format('topic_id, vf, vt', 'vtext')}), dgram AS ({_GRAMS.format('doc_id', '(SELECT * FROM corpus WHERE doc_id IN (SELECT doc_id FROM best))')}), sizes AS (SELECT doc_id, count(*) AS n FROM dgram GROUP BY 1),
nm AS (SELECT topic_id, doc_id, vf, vt, count(*) / CAST(n AS DOUBLE) AS share FROM best JOIN dgram USING (doc_id) JOIN sizes USING (doc_id) JOIN vgram USING (topic_id, g) GROUP BY topic_id, doc_id, vf, vt, n), matches AS (SELECT *, round(1 - share, 9) AS dist FROM nm WHERE share >= 0.5),
near AS (SELECT DISTINCT topic_id, doc_id, unnest(range(vf, vt + 1)) AS month_ix FROM (SELECT *, min(dist) OVER (PARTITION BY topic_id, doc_id) AS least FROM matches) WHERE dist = least),
latest AS (SELECT topic_id, doc_id, max(month_ix) AS month_ix FROM near GROUP BY 1, 2), {s.sql_grid()},
hist AS (SELECT month_ix, coalesce(n, 0) AS n FROM grid LEFT JOIN (SELECT month_ix, CAST(count(*) AS DOUBLE) AS n FROM near GROUP BY 1) USING (month_ix))"""
_CURVE = f"(WITH {s.sql_topic_perplexity({MIX: s.MIXES[MIX]})}, {s.sql_curve()} SELECT * FROM curve)"

ORACLE_SQL = {
    "bm25_top10": f"{_BASE} SELECT topic_id, doc_id, rank, score FROM best",
    "bm25_top10_scan": f"{_BASE} SELECT topic_id, doc_id, rank, score FROM best",
    "ngram_matches": f"{_NGRAM} SELECT topic_id, doc_id, vf AS version_from, vt AS version_to, round(share, 6) AS share FROM matches",
    "ngram_histogram": f"{_NGRAM} SELECT month_ix, n FROM hist",
    "ngram_histogram_split": f"{_NGRAM} SELECT month_ix, round(coalesce(n, 0), 4) AS n FROM grid LEFT JOIN (SELECT month_ix, sum(w) AS n FROM (SELECT month_ix, 1.0 / count(*) OVER (PARTITION BY topic_id, doc_id)::DOUBLE AS w FROM near) GROUP BY 1) USING (month_ix)",
    "ngram_by_subcorpus": f"{_NGRAM}, parts AS (SELECT subcorpus, month_ix, count(*)::DOUBLE AS n FROM near JOIN corpus USING (doc_id) GROUP BY 1, 2) SELECT subcorpus, month_ix, coalesce(n, 0) AS n FROM (SELECT DISTINCT subcorpus FROM parts) CROSS JOIN grid LEFT JOIN parts USING (subcorpus, month_ix)",
    "ngram_share_older": f"{_NGRAM} SELECT count(*)::DOUBLE AS matched, round(avg(CASE WHEN month_ix < {DUMP} THEN 1.0 ELSE 0.0 END), 4) AS share_older FROM latest",
    "ngram_curve_corr": f"{_NGRAM}, met AS (SELECT c.model, c.month_ix, c.rel, h.n FROM {_CURVE} c JOIN hist h USING (month_ix)), ranks AS (SELECT *, rank() OVER (ORDER BY rel) + (count(*) OVER (PARTITION BY rel) - 1) / 2.0 AS rr, rank() OVER (ORDER BY n) + (count(*) OVER (PARTITION BY n) - 1) / 2.0 AS rn FROM met) SELECT model, round(corr(rel, n), 4) AS pearson, round(corr(rr, rn), 4) AS spearman FROM ranks GROUP BY 1",
    "ngram_dump_age": f"{_NGRAM}, aged AS (SELECT subcorpus, CAST(substr(subcorpus, 6) AS INTEGER) AS dump_month, CAST(substr(subcorpus, 6) AS INTEGER) - month_ix AS age FROM latest JOIN corpus USING (doc_id) WHERE subcorpus LIKE 'crawl%') SELECT subcorpus, dump_month, count(*) AS n, quantile_cont(age, 0.5) AS median_age, round(avg(CASE WHEN age > 0 THEN 1.0 ELSE 0.0 END), 4) AS share_old, round(avg(age) - quantile_cont(age, 0.5), 4) AS skew FROM aged GROUP BY 1, 2",
    "ngram_copies": f"{_NGRAM}, per AS (SELECT topic_id, count(*) AS documents, count(DISTINCT array_to_string(toks, ' ')) AS texts FROM (SELECT DISTINCT topic_id, doc_id FROM near) JOIN corpus USING (doc_id) GROUP BY 1) SELECT topic_id, documents, documents - texts AS copies, texts AS versions FROM per",
    "static_inclusion": f"WITH {s.sql_topic_perplexity({m: s.MIXES[m] for m in (MIX, 'webonly')})} SELECT model, count(*) FILTER (ppl < 100.0) AS included, count(*) AS versions FROM ppl GROUP BY 1",
    "exact_inclusion": f"{_BASE}, {_VTEXT} SELECT topic_id, vf AS version_from, vt AS version_to FROM vtext WHERE array_to_string(toks, ' ') IN (SELECT array_to_string(toks, ' ') FROM corpus)",
}
