"""Workloads on the probe side: versions, curves, cutoffs and their ablations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import head_tokens, tokens
from ..functions.timegrid import months
from ..plans import ablate, compare, curves, ngram_lm, probes
from ..sources.tables import stored, table
from . import setup as s

SIZES = [2500, 1000, 500, 250, 100, 50]


def _rounded(df: DataFrame, *cols: str) -> DataFrame:
    return df.select(*(F.round(c, 4).alias(c) if c in cols else F.col(c) for c in df.columns))


def ev_versions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every distinct version of every topic, by its months and a digest of its words."""
    packed = probes.packed_set(table(spark, sf_dir, "documents", "doc_id", "text"), s.edits(spark, sf_dir), s.chosen_topics(spark, sf_dir), s.TOPIC_TOKENS)
    return probes.whole_versions(packed.withColumn("tail", F.lit(""))).select("topic_id", "version_from", "version_to", F.md5(F.col("text").cast("binary")).alias("digest"))


def ev_topics(spark: SparkSession, sf_dir: str) -> DataFrame:
    return s.chosen_topics(spark, sf_dir)


def dt_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _dated(spark, sf_dir).select("doc_id", "month_ix")


def _dated(spark, sf_dir):
    return probes.dated_set(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "orders", "o_orderkey", "o_orderdate"), s.PER_BUCKET)


def _dated_perplexity(spark: SparkSession, sf_dir: str, order: int = 2) -> DataFrame:
    """Dated documents under a model of the earlier ones: (model, doc_id, month_ix, ppl)."""
    docs = _dated(spark, sf_dir)
    trained = docs.where(F.col("month_ix") <= s.TRAINED_UNTIL).select(tokens(F.col("text")).alias("toks"))
    probe = stored(ngram_lm.grams_of_arrays(docs.select("doc_id", "month_ix", head_tokens(F.col("text"), s.DATED_TOKENS).alias("toks")), "toks", "doc_id", "month_ix"))
    model = ngram_lm.train(ngram_lm.grams_of_arrays(trained, "toks").select("a", "b", "c", F.lit(1).cast("long").alias("dt")), ["dt"], probe)
    scored = ngram_lm.score(model, probe, order)
    return scored.groupBy("doc_id", "month_ix").agg(F.exp(-F.avg("lp_dt")).alias("ppl")).select(F.lit("dt").alias("model"), "doc_id", "month_ix", "ppl")


def dt_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Newspaper experiment: the curve rises behind the last month trained on."""
    return _rounded(curves.relative(curves.trimmed_mean(_dated_perplexity(spark, sf_dir), item="doc_id")), "ppl", "rel")


def dt_cutoff_rise(spark: SparkSession, sf_dir: str) -> DataFrame:
    curve = curves.relative(curves.trimmed_mean(_dated_perplexity(spark, sf_dir), item="doc_id"))
    return curves.effective_cutoff(curve, "rise")


def _curve(spark, sf_dir, mixes, order=2, pruned=True):
    return curves.relative(curves.trimmed_mean(s.topic_perplexity(spark, sf_dir, mixes, order, pruned)))


def ev_curve_curated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Models of the curated corpus: a sharp minimum at the up-sampled dump."""
    return _rounded(_curve(spark, sf_dir, ["curated"]), "ppl", "rel")


def ev_curve_whole(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As the curated curve, from counts of all grams of the corpus instead of the probes' grams; the numbers are the same."""
    return _rounded(_curve(spark, sf_dir, ["curated"], pruned=False), "ppl", "rel")


def ev_curve_webonly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No dump at all, only copies: a minimum all the same."""
    return _rounded(_curve(spark, sf_dir, ["webonly"]), "ppl", "rel")


def ev_curve_multidump(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Many crawl dumps: minima earlier than the dumps stated."""
    return _rounded(_curve(spark, sf_dir, ["multidump_early", "multidump_mid", "multidump_late"]), "ppl", "rel")


def ev_curve_order3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(_curve(spark, sf_dir, ["multidump_mid"], order=3), "ppl", "rel")


def ev_curve_pruned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order 3 with counts of the probes' grams only."""
    return _rounded(_curve(spark, sf_dir, ["curated"], order=3, pruned=True), "ppl", "rel")


def ev_effective_cutoffs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every model's effective cutoff, its width, the date stated and the gap."""
    curve = stored(_curve(spark, sf_dir, list(s.MIXES)))
    cards = compare.cards(spark, s.STATED)
    out = compare.gap(curves.effective_cutoff(curve), cards).join(curves.sharpness(curve), "model")
    return out.withColumns({c: F.col(c).cast("double") for c in ("stated", "gap")})


def ev_cutoff_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The cutoff as a distribution: months near the minimum and the largest weight."""
    spread = curves.cutoff_spread(_curve(spark, sf_dir, ["curated", "webonly"]))
    return spread.select("model", F.array_join("months", ",").alias("months"), F.round(F.array_max(F.transform("weights", lambda x: x["weight"])), 4).alias("top_weight"), F.round(F.aggregate("weights", F.lit(0.0), lambda a, x: a + x["weight"]), 4).alias("total"))


def ev_single_topic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One document's own curve: the topic of least id."""
    ppl = s.topic_perplexity(spark, sf_dir, ["curated"])
    first = s.chosen_topics(spark, sf_dir).agg(F.min("topic_id").alias("topic_id"))
    return _rounded(ppl.join(F.broadcast(first), "topic_id").select("model", "topic_id", "month_ix", "ppl"), "ppl")


def ev_absolute(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Unscaled, untrimmed means: the baseline the relative curve is set against."""
    return _rounded(curves.absolute(s.topic_perplexity(spark, sf_dir, ["curated", "webonly"])), "ppl")


def trimmed_vs_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One month of redirect-like pages (topics whose id is a multiple of 50, perplexity times 50): trimmed, plain and median."""
    ppl = s.topic_perplexity(spark, sf_dir, ["curated"])
    odd = (F.col("month_ix") == 40) & (F.col("topic_id") % 50 == 0)
    ppl = stored(ppl.withColumn("ppl", F.when(odd, F.col("ppl") * 50).otherwise(F.col("ppl"))))
    keys = ["model", "month_ix"]
    out = curves.trimmed_mean(ppl).select(*keys, F.col("ppl").alias("trimmed"))
    for how in ("mean", "median"):
        out = out.join(curves.trimmed_mean(ppl, agg=how).select(*keys, F.col("ppl").alias(how)), keys)
    return _rounded(out, "trimmed", "mean", "median")


def scale_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Smaller models: orders 1 to 3, and training on one, two and four eighths of the ids, against all."""
    chosen, intervals = s.topic_intervals(spark, sf_dir)
    intervals = stored(intervals)
    mixes = {"curated": s.MIXES["curated"]}
    parts = []
    for order, eighths in ((1, 8), (2, 8), (3, 8), (2, 4), (2, 2), (2, 1)):
        grams = stored(ngram_lm.grams_of_intervals(intervals, order))
        part = (lambda e: lambda x: F.col(x) % 8 < e)(eighths) if eighths < 8 else None
        model = ngram_lm.train(s.corpus_grams(spark, sf_dir, chosen, grams, mixes, part), ["curated"], grams)
        ppl = ngram_lm.monthly_perplexity(ngram_lm.score(model, grams, order), months(spark), ["curated"])
        parts.append(ppl.withColumn("model", F.lit(f"order{order}_{eighths}of8")))
    curve = curves.relative(curves.trimmed_mean(ablate.union(parts)))
    return ablate.summary(curve)


def docs_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fewer topics a month: the most edited x of them, scored by the full model."""
    mixes = ["multidump_early", "multidump_mid", "multidump_late"]
    ppl = stored(s.topic_perplexity(spark, sf_dir, mixes))
    ranked = ablate.ranked_topics(s.chosen_topics(spark, sf_dir))
    return ablate.summary(curves.relative(curves.trimmed_mean(ablate.by_size(ppl, ranked, SIZES))))


def docs_stability(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How far cutoffs move, and how much curves vary, over the numbers of topics."""
    return ablate.stability(docs_ablation(spark, sf_dir), "5000")


def trimmed_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trimming by sketched bounds instead of ranks, for months of very many items: beside the exact mean."""
    ppl = stored(s.topic_perplexity(spark, sf_dir, ["curated"]))
    keys = ["model", "month_ix"]
    exact = curves.trimmed_mean(ppl).select(*keys, F.col("ppl").alias("trimmed"), F.col("n").alias("n"))
    sketched = curves.trimmed_mean(ppl, approx=True).select(*keys, F.col("ppl").alias("_p"), F.col("n").alias("_n"))
    near = (F.abs(F.col("_p") / F.col("trimmed") - 1) < 0.02) & (F.abs(F.col("_n") - F.col("n")) <= F.greatest(F.lit(2), F.col("n") * 0.01))
    return _rounded(exact.join(sketched, keys).select(*keys, "trimmed", "n", near.alias("near")), "trimmed")


DENSITIES = {"every": 1, "second": 2, "fourth": 4}


def dedup_vs_upsampled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Only the dump's weight changes (3 or 1), with old copies of every, every 2nd and every 4th topic."""
    chosen, intervals = s.topic_intervals(spark, sf_dir)
    grams = stored(ngram_lm.grams_of_intervals(intervals, 2))
    names, weights = [], []
    for name, d in DENSITIES.items():
        for w in (3, 1):
            old = F.when(F.col("topic_id") % d == 0, ngram_lm.planted_weight({24: 1, 36: 1})).otherwise(0)
            names.append(f"{name}_x{w}")
            weights.append((ngram_lm.planted_weight({60: w}) + old).cast("long").alias(names[-1]))
    docs = table(spark, sf_dir, "documents", "doc_id", "text").join(chosen.select(F.col("topic_id").alias("doc_id")), "doc_id", "left_anti")
    background = ngram_lm.grams_of_arrays(docs.select(tokens(F.col("text")).alias("toks")), "toks").select("a", "b", "c", *(F.lit(1).cast("long").alias(m) for m in names))
    model = ngram_lm.train(background.union(grams.select("a", "b", "c", *weights)), names, grams)
    curve = stored(curves.relative(curves.trimmed_mean(ngram_lm.monthly_perplexity(ngram_lm.score(model, grams, 2), months(spark), names))))
    return curves.effective_cutoff(curve).join(curves.sharpness(curve), "model")


def static_control(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A resource that never changes has a flat curve, so no relative perplexity and no cutoff."""
    items = probes.static_set(table(spark, sf_dir, "benchmark", "item_id", "text"), spark)
    grams = ngram_lm.grams_of_intervals(items, 2)
    docs = table(spark, sf_dir, "documents", "text").select(tokens(F.col("text")).alias("toks"))
    model = ngram_lm.train(ngram_lm.grams_of_arrays(docs, "toks").select("a", "b", "c", F.lit(1).cast("long").alias("static")), ["static"])
    curve = curves.relative(curves.trimmed_mean(ngram_lm.monthly_perplexity(ngram_lm.score(model, grams, 2), months(spark), ["static"])))
    return _rounded(curve, "ppl", "rel")


QUERIES = {f.__name__: f for f in (ev_topics, ev_versions, dt_buckets, dt_curve, dt_cutoff_rise, ev_curve_curated, ev_curve_whole, ev_curve_webonly, ev_curve_multidump, ev_curve_order3, ev_curve_pruned, ev_effective_cutoffs, ev_cutoff_spread, ev_single_topic, ev_absolute, trimmed_vs_mean, scale_ablation, docs_ablation, docs_stability, trimmed_approx, dedup_vs_upsampled, static_control)}

# --- SQL -------------------------------------------------------------------

_CURVE = "SELECT model, month_ix, round(ppl, 4) AS ppl, n, round(rel, 4) AS rel FROM curve"
_DATED = f"""dated AS (SELECT doc_id, month_ix, text FROM (SELECT doc_id, {s.MONTH} AS month_ix, text, row_number() OVER (PARTITION BY {s.MONTH} ORDER BY md5('dt' || doc_id), doc_id) AS r FROM documents JOIN orders ON doc_id = o_orderkey) WHERE r <= {s.PER_BUCKET})"""
_DATED_PPL = f"""{_DATED}, dtok AS (SELECT doc_id, month_ix, {s.sql_tokens('text')} AS toks FROM dated),
corp AS (SELECT doc_id AS seq, generate_subscripts(toks, 1) AS pos, unnest(toks) AS c, 1 AS w_dt FROM dtok WHERE month_ix <= {s.TRAINED_UNTIL}),
probe AS (SELECT doc_id, month_ix, generate_subscripts(toks[1:{s.DATED_TOKENS}], 1) AS pos, unnest(toks[1:{s.DATED_TOKENS}]) AS c FROM dtok),
{s.sql_model('corp', 'probe', ['dt'], 2, 'doc_id, month_ix')}, ppl AS (SELECT 'dt' AS model, doc_id, month_ix, exp(-l_dt) AS ppl FROM sc), {s.sql_curve(item='doc_id')}"""


def _sql(mixes: list[str], order: int = 2, part: str = "TRUE") -> str:
    return f"WITH {s.sql_topic_perplexity({m: s.MIXES[m] for m in mixes}, order, part=part)}, {s.sql_curve()}"


def _summary(src: str) -> str:
    return f"""SELECT a.model, a.cutoff, c.width, c.deviation FROM argmins a JOIN (SELECT model, count(*) FILTER (rel <= 0.05) AS width, round(stddev_samp(rel), 4) AS deviation FROM {src} GROUP BY 1) c ON a.model = c.model"""


def _scale() -> str:
    parts = []
    for order, eighths in ((1, 8), (2, 8), (3, 8), (2, 4), (2, 2), (2, 1)):
        body = s.sql_topic_perplexity({"curated": s.MIXES["curated"]}, order, part=f"x % 8 < {eighths}" if eighths < 8 else "TRUE")
        parts.append(f"SELECT * FROM (WITH {body} SELECT 'order{order}_{eighths}of8' AS model, topic_id, month_ix, ppl FROM ppl)")
    return f"WITH ppl AS ({' UNION ALL '.join(parts)}), {s.sql_curve()}, {s.SQL_ARGMIN} {_summary('curve')}"


def _sizes() -> str:
    mixes = ["multidump_early", "multidump_mid", "multidump_late"]
    sized = " UNION ALL ".join(f"SELECT model || '_{x}' AS model, topic_id, month_ix, ppl FROM ppl JOIN ranked_topics USING (topic_id) WHERE rk <= {x}" for x in [5000, *SIZES])
    return f"""WITH {s.sql_topic_perplexity({m: s.MIXES[m] for m in mixes})}, ranked_topics AS (SELECT topic_id, row_number() OVER (ORDER BY n_edits DESC, topic_id) AS rk FROM topics), sized AS ({sized}), {s.sql_curve(src='sized')}, {s.SQL_ARGMIN} {_summary('curve')}"""


def _dedup() -> str:
    names = [(f"{n}_x{w}", d, w) for n, d in DENSITIES.items() for w in (3, 1)]
    body = s.sql_topic_perplexity({n: {60: w, 24: 1, 36: 1} for n, _, w in names})
    for n, d, w in names:  # old copies only of every d-th topic
        body = body.replace(f"CASE m WHEN 24 THEN 1 WHEN 36 THEN 1 WHEN 60 THEN {w} ELSE 0 END", f"CASE WHEN m = 60 THEN {w} WHEN ((seq - 10000000) // 100) % {d} = 0 THEN 1 ELSE 0 END", 1)
    return f"WITH {body}, {s.sql_curve()}, {s.SQL_ARGMIN} SELECT a.model, a.cutoff, w.width FROM argmins a JOIN (SELECT model, count(*) FILTER (rel <= 0.05) AS width FROM curve GROUP BY 1) w ON a.model = w.model"


_STATED = " UNION ALL ".join(f"SELECT '{m}' AS model, CAST({'NULL' if x is None else x} AS INTEGER) AS stated" for m, x in s.STATED.items())

ORACLE_SQL = {
    "ev_topics": f"WITH {s.sql_topics()} SELECT topic_id, n_edits, first_month FROM topics",
    "ev_versions": f"WITH {s.sql_topics()} SELECT topic_id, vf AS version_from, vt AS version_to, md5(string_agg(token, ' ' ORDER BY pos)) AS digest FROM vtok GROUP BY 1, 2, 3",
    "dt_buckets": f"WITH {_DATED} SELECT doc_id, month_ix FROM dated",
    "dt_curve": f"WITH {_DATED_PPL} {_CURVE}",
    "dt_cutoff_rise": f"WITH {_DATED_PPL}, {s.SQL_RISE} SELECT model, cutoff FROM rises",
    "ev_curve_curated": f"{_sql(['curated'])} {_CURVE}",
    "ev_curve_webonly": f"{_sql(['webonly'])} {_CURVE}",
    "ev_curve_multidump": f"{_sql(['multidump_early', 'multidump_mid', 'multidump_late'])} {_CURVE}",
    "ev_curve_order3": f"{_sql(['multidump_mid'], 3)} {_CURVE}",
    "ev_curve_pruned": f"{_sql(['curated'], 3)} {_CURVE}",
    "ev_curve_whole": f"{_sql(['curated'])} {_CURVE}",
    "ev_effective_cutoffs": f"{_sql(list(s.MIXES))}, {s.SQL_ARGMIN}, cards AS ({_STATED}) SELECT a.model, a.cutoff, CAST(stated AS DOUBLE) AS stated, CAST(a.cutoff - stated AS DOUBLE) AS gap, width FROM argmins a JOIN cards c ON c.model = a.model JOIN (SELECT model, count(*) FILTER (rel <= 0.05) AS width FROM curve GROUP BY 1) w ON w.model = a.model",
    "ev_cutoff_spread": f"{_sql(['curated', 'webonly'])}, shares AS (SELECT *, exp(-rel / 0.05) / sum(exp(-rel / 0.05)) OVER (PARTITION BY model) AS weight FROM curve) SELECT model, string_agg(CASE WHEN rel <= 0.05 THEN CAST(month_ix AS VARCHAR) END, ',' ORDER BY month_ix) AS months, round(max(weight), 4) AS top_weight, round(sum(weight), 4) AS total FROM shares GROUP BY 1",
    "ev_single_topic": f"{_sql(['curated'])} SELECT model, topic_id, month_ix, round(ppl, 4) AS ppl FROM ppl WHERE topic_id = (SELECT min(topic_id) FROM topics)",
    "ev_absolute": f"{_sql(['curated', 'webonly'])} SELECT model, month_ix, round(avg(ppl), 4) AS ppl, count(*) AS n FROM ppl GROUP BY 1, 2",
    "trimmed_vs_mean": f"WITH {s.sql_topic_perplexity({'curated': s.MIXES['curated']})}, odd AS (SELECT model, topic_id, month_ix, CASE WHEN month_ix = 40 AND topic_id % 50 = 0 THEN ppl * 50 ELSE ppl END AS ppl FROM ppl), {s.sql_curve(src='odd')} SELECT c.model, c.month_ix, round(c.ppl, 4) AS trimmed, round(o.mean, 4) AS mean, round(o.median, 4) AS median FROM curve c JOIN (SELECT model, month_ix, avg(ppl) AS mean, quantile_cont(ppl, 0.5) AS median FROM odd GROUP BY 1, 2) o ON o.model = c.model AND o.month_ix = c.month_ix",
    "scale_ablation": _scale(),
    "docs_ablation": _sizes(),
    "docs_stability": f"WITH sums AS ({_sizes()}), named AS (SELECT regexp_extract(model, '^(.*)_([^_]*)$', 1) AS family, regexp_extract(model, '^(.*)_([^_]*)$', 2) AS setting, cutoff, deviation FROM sums) SELECT n.family, max(abs(n.cutoff - r.cutoff)) AS max_shift, round(avg(n.deviation), 4) AS mean_deviation FROM named n JOIN (SELECT family, cutoff FROM named WHERE setting = '5000') r ON r.family = n.family GROUP BY 1",
    "trimmed_approx": f"{_sql(['curated'])} SELECT model, month_ix, round(ppl, 4) AS trimmed, n, TRUE AS near FROM curve",
    "dedup_vs_upsampled": _dedup(),
    "static_control": f"""WITH {s.sql_grid()}, corp AS (SELECT doc_id AS seq, generate_subscripts(toks, 1) AS pos, unnest(toks) AS c, 1 AS w_static FROM (SELECT doc_id, {s.sql_tokens('text')} AS toks FROM documents)),
probe AS (SELECT item_id AS topic_id, generate_subscripts(toks, 1) AS pos, unnest(toks) AS c FROM (SELECT item_id, {s.sql_tokens('text')} AS toks FROM benchmark)), {s.sql_model('corp', 'probe', ['static'], 2, 'topic_id')},
ppl AS (SELECT 'static' AS model, topic_id, month_ix, exp(-l_static) AS ppl FROM sc, grid), {s.sql_curve()} SELECT model, month_ix, round(ppl, 4) AS ppl, n, CAST(NULL AS DOUBLE) AS rel FROM curve""",
}
