"""Parameters and shared inputs of the experiment workloads, for Spark and for SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import ACCENTED, PLAIN, tokens
from ..functions.timegrid import LAST_MONTH, months
from ..plans import ngram_lm, probes
from ..sources.tables import stored, table

TOPICS, TOPIC_TOKENS, DATED_TOKENS, PER_BUCKET, TRAINED_UNTIL = 5000, 512, 256, 500, 48

#: Training mixes: month of a planted version -> its weight. Background documents stand beside in each.
MIXES = {
    "curated": {60: 3, 24: 1, 36: 1},
    "curated_dedup": {60: 1, 24: 1, 36: 1},
    "webonly": {44: 1, 48: 1, 52: 1},
    "multidump_early": {8: 1, 16: 1, 24: 1, 32: 1, 40: 1},
    "multidump_mid": {16: 1, 24: 1, 28: 1, 72: 1},
    "multidump_late": {20: 1, 36: 1, 52: 1, 60: 1, 68: 1, 72: 1},
}
#: Model cards: the date stated for the resource, unknown where none is.
STATED = {"curated": 60, "curated_dedup": 60, "webonly": None, "multidump_early": 68, "multidump_mid": 72, "multidump_late": 75}


def edits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return probes.edit_log(table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate"), table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey"))


def chosen_topics(spark: SparkSession, sf_dir: str, k: int = TOPICS) -> DataFrame:
    return probes.topics(table(spark, sf_dir, "documents", "doc_id", "text"), edits(spark, sf_dir), k)


def topic_intervals(spark: SparkSession, sf_dir: str, k: int = TOPICS) -> tuple[DataFrame, DataFrame]:
    """The topics and their word intervals."""
    chosen = chosen_topics(spark, sf_dir, k)
    return chosen, probes.evolving_set(table(spark, sf_dir, "documents", "doc_id", "text"), edits(spark, sf_dir), chosen, TOPIC_TOKENS)


def corpus_grams(spark: SparkSession, sf_dir: str, chosen: DataFrame, grams: DataFrame, mixes: dict[str, dict[int, int]], part=None) -> DataFrame:
    """Weighted grams of background documents and of planted versions, a weight column a mix.

    ``part``: a condition on the documents and topics that are trained on, as (documents' condition, topics' condition).
    """
    docs = table(spark, sf_dir, "documents", "doc_id", "text").join(chosen.select(F.col("topic_id").alias("doc_id")), "doc_id", "left_anti")
    if part is not None:
        docs, grams = docs.where(part("doc_id")), grams.where(part("topic_id"))
    background = ngram_lm.grams_of_arrays(docs.select(tokens(F.col("text")).alias("toks")), "toks").select("a", "b", "c", *(F.lit(1).cast("long").alias(m) for m in mixes))
    return background.union(grams.select("a", "b", "c", *(ngram_lm.planted_weight(at).alias(m) for m, at in mixes.items())))


def topic_perplexity(spark: SparkSession, sf_dir: str, mixes: list[str], order: int = 2, pruned: bool = True, k: int = TOPICS) -> DataFrame:
    """(model, topic_id, month_ix, ppl) of every topic in every month under each mix."""
    chosen, intervals = topic_intervals(spark, sf_dir, k)
    grams = stored(ngram_lm.grams_of_intervals(intervals, order))  # trained on and scored
    some = {m: MIXES[m] for m in mixes}
    model = ngram_lm.train(corpus_grams(spark, sf_dir, chosen, grams, some), list(some), grams if pruned else None)
    return ngram_lm.monthly_perplexity(ngram_lm.score(model, grams, order), months(spark), list(some))


# --- SQL -------------------------------------------------------------------

MONTH = "(year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1"


def sql_fold(text: str) -> str:
    return f"lower(translate({text}, '{ACCENTED}', '{PLAIN}'))"


def sql_canonical(text: str) -> str:
    return rf"trim(regexp_replace({sql_fold(text)}, '\s+', ' ', 'g'))"


def sql_tokens(text: str) -> str:
    return f"CASE WHEN {sql_canonical(text)} = '' THEN [] ELSE string_split({sql_canonical(text)}, ' ') END"


def sql_topics(k: int = TOPICS) -> str:
    """CTEs words, edits, topics, base, hits, ints, vers, vtok."""
    return f"""words AS (SELECT doc_id, {sql_tokens('text')} AS toks FROM documents),
edits AS (SELECT o_custkey AS topic_id, {MONTH} AS m, o_orderkey AS ok, l_linenumber AS ln, l_partkey AS pk FROM orders JOIN lineitem ON l_orderkey = o_orderkey),
topics AS (SELECT e.topic_id, count(*) AS n_edits, min(m) AS first_month FROM edits e JOIN words w ON w.doc_id = e.topic_id AND len(w.toks) >= 100 GROUP BY 1 HAVING min(m) <= 5 ORDER BY n_edits DESC, topic_id LIMIT {k}),
base AS (SELECT topic_id, toks[1:{TOPIC_TOKENS}] AS toks, len(toks[1:{TOPIC_TOKENS}]) AS n FROM topics JOIN words ON doc_id = topic_id),
hits AS (SELECT topic_id, m, pos, token FROM (SELECT e.topic_id, m, (ok * 31 + ln * 97) % n AS pos, 'p' || pk AS token, row_number() OVER (PARTITION BY e.topic_id, (ok * 31 + ln * 97) % n, m ORDER BY ok DESC, ln DESC, pk DESC) AS r FROM edits e JOIN base b ON b.topic_id = e.topic_id) WHERE r = 1),
states AS (SELECT topic_id, generate_subscripts(toks, 1) - 1 AS pos, unnest(toks) AS token, 0 AS f, 0 AS edited FROM base UNION ALL SELECT topic_id, pos, token, m, 1 FROM hits),
ints AS (SELECT * FROM (SELECT topic_id, pos, token, f, coalesce(lead(f) OVER (PARTITION BY topic_id, pos ORDER BY f, edited) - 1, {LAST_MONTH}) AS t FROM states) WHERE f <= t),
vers AS (SELECT topic_id, vf, coalesce(lead(vf) OVER (PARTITION BY topic_id ORDER BY vf) - 1, {LAST_MONTH}) AS vt FROM (SELECT DISTINCT topic_id, f AS vf FROM ints UNION SELECT topic_id, 0 FROM base)),
vtok AS (SELECT v.topic_id, vf, vt, pos, token FROM vers v JOIN ints i ON i.topic_id = v.topic_id AND f <= vf AND vf <= t)"""


def sql_grid(step: int = 1) -> str:
    return f"grid AS (SELECT unnest(range(0, {LAST_MONTH + 1}, {step})) AS month_ix)"


def sql_model(corpus: str, probe: str, mixes: list[str], order: int, keys: str) -> str:
    """CTEs that train on ``corpus`` (seq, pos, c, w_<mix>) and score ``probe`` (keys, pos, c), as sc (keys, l_<mix>)."""
    w = ", ".join(f"sum(w_{m}) AS {m}" for m in mixes)
    lam, v = ngram_lm.LAMBDA, ngram_lm.VOCABULARY

    def p(m: str) -> str:
        out = f"(coalesce(n1.{m}, 0) + 1) / CAST(tot.{m} + {v} AS DOUBLE)"
        for k in range(2, order + 1):
            out = f"CASE WHEN coalesce(h{k - 1}.{m}, 0) > 0 THEN {lam} * coalesce(n{k}.{m}, 0) / CAST(h{k - 1}.{m} AS DOUBLE) + {1 - lam} * ({out}) ELSE {out} END"
        return out

    joins = "LEFT JOIN n1 ON n1.c = g.c"
    if order >= 2:
        joins += " LEFT JOIN n2 ON n2.b = g.b AND n2.c = g.c LEFT JOIN n1 h1 ON h1.c = g.b"
    if order >= 3:
        joins += " LEFT JOIN n3 ON n3.a = g.a AND n3.b = g.b AND n3.c = g.c LEFT JOIN n2 h2 ON h2.b = g.a AND h2.c = g.b"
    return f"""cg AS (SELECT *, lag(c, 1) OVER s AS b, lag(c, 2) OVER s AS a FROM {corpus} WINDOW s AS (PARTITION BY seq ORDER BY pos)),
pg AS (SELECT *, lag(c, 1) OVER s AS b, lag(c, 2) OVER s AS a FROM {probe} WINDOW s AS (PARTITION BY {keys} ORDER BY pos)),
tot AS (SELECT {w} FROM cg), n1 AS (SELECT c, {w} FROM cg GROUP BY 1), n2 AS (SELECT b, c, {w} FROM cg WHERE b IS NOT NULL GROUP BY 1, 2), n3 AS (SELECT a, b, c, {w} FROM cg WHERE a IS NOT NULL GROUP BY 1, 2, 3),
sc AS (SELECT {", ".join("g." + k.strip() for k in keys.split(","))}, {", ".join(f"avg(ln({p(m)})) AS l_{m}" for m in mixes)} FROM pg g CROSS JOIN tot {joins} GROUP BY ALL)"""


def sql_topic_perplexity(mixes: dict[str, dict[int, int]], order: int = 2, k: int = TOPICS, part: str = "TRUE") -> str:
    """CTEs up to ppl (model, topic_id, month_ix, ppl). ``part``: a condition on the id ``x`` that is trained on."""
    at = sorted({m for x in mixes.values() for m in x})
    weight = lambda x: "CASE m " + " ".join(f"WHEN {m} THEN {x[m]}" for m in sorted(x)) + " ELSE 0 END"
    return f"""{sql_topics(k)}, {sql_grid()},
bg AS (SELECT doc_id AS seq, generate_subscripts(toks, 1) AS pos, unnest(toks) AS c FROM words WHERE doc_id NOT IN (SELECT topic_id FROM topics) AND {part.replace('x', 'doc_id')}),
pl AS (SELECT 10000000 + topic_id * 100 + m AS seq, pos, token AS c, m FROM ints JOIN (SELECT unnest({at}) AS m) ON f <= m AND m <= t WHERE {part.replace('x', 'topic_id')}),
corp AS (SELECT seq, pos, c, {", ".join(f"1 AS w_{m}" for m in mixes)} FROM bg UNION ALL SELECT seq, pos, c, {", ".join(weight(x) for x in mixes.values())} FROM pl),
probe AS (SELECT topic_id, vf, vt, pos, token AS c FROM vtok),
{sql_model('corp', 'probe', list(mixes), order, 'topic_id, vf, vt')},
ppl AS ({" UNION ALL ".join(f"SELECT '{m}' AS model, topic_id, month_ix, exp(-l_{m}) AS ppl FROM sc JOIN grid ON vf <= month_ix AND month_ix <= vt" for m in mixes)})"""


def sql_curve(trim: float = 0.025, item: str = "topic_id", src: str = "ppl") -> str:
    """CTEs curve (model, month_ix, ppl, n, rel)."""
    return f"""ranked AS (SELECT model, month_ix, ppl, row_number() OVER (PARTITION BY model, month_ix ORDER BY ppl, {item}) AS r, count(*) OVER (PARTITION BY model, month_ix) AS n FROM {src}),
means AS (SELECT model, month_ix, avg(ppl) AS ppl, count(*) AS n FROM ranked WHERE floor(n * {trim}) < r AND r <= n - floor(n * {trim}) GROUP BY 1, 2),
curve AS (SELECT *, (ppl - min(ppl) OVER w) / nullif(max(ppl) OVER w - min(ppl) OVER w, 0) AS rel FROM means WINDOW w AS (PARTITION BY model))"""


SQL_ARGMIN = "argmins AS (SELECT model, month_ix AS cutoff FROM (SELECT *, row_number() OVER (PARTITION BY model ORDER BY rel, month_ix) AS r FROM curve WHERE rel IS NOT NULL) WHERE r = 1)"
SQL_RISE = """splits AS (SELECT model, month_ix, count(*) OVER w AS n1, sum(rel) OVER w AS s1, count(*) OVER (PARTITION BY model) AS n, sum(rel) OVER (PARTITION BY model) AS s FROM curve WINDOW w AS (PARTITION BY model ORDER BY month_ix ROWS UNBOUNDED PRECEDING)),
gains AS (SELECT *, s1 / n1 AS m1, (s - s1) / (n - n1) AS m2 FROM splits WHERE n1 < n),
rises AS (SELECT model, month_ix AS cutoff FROM (SELECT *, row_number() OVER (PARTITION BY model ORDER BY n1 * (n - n1) / CAST(n AS DOUBLE) * (m2 - m1) * (m2 - m1) DESC, month_ix) AS r FROM gains WHERE m2 > m1) WHERE r = 1)"""
