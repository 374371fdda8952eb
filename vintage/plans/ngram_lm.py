"""Interpolated n-gram models of orders 1 to 3, trained and scored in plans.

p1 = (c(w) + 1) / (N + V); pn = L * c(h, w) / c(h) + (1 - L) * p(n-1) where the
history h was seen, else p(n-1). One pass over one union of corpora trains a
model for each *mix*: a gram row carries a weight column a mix, so an up-sampled
or left-out part is a number, never a copy.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import shifted
from ..sources.tables import stored

#: Interpolation weight and vocabulary size of the model.
LAMBDA, VOCABULARY = 0.6, 50_000
BROADCAST_GRAMS = 2_000_000


def grams_of_arrays(docs: DataFrame, toks: str, *keep: str) -> DataFrame:
    """(keep..., pos, a, b, c): each token c with the two before it, without a shuffle."""
    zipped = F.arrays_zip(shifted(F.col(toks), 2).alias("a"), shifted(F.col(toks), 1).alias("b"), F.col(toks).alias("c"))
    return docs.select(*keep, F.posexplode(zipped).alias("pos", "g")).select(*keep, "pos", "g.a", "g.b", "g.c")


def grams_of_intervals(intervals: DataFrame, order: int = 3) -> DataFrame:
    """(topic_id, pos, a, b, c, valid_from, valid_to): grams as intervals of the months they stand.

    Neighbouring positions meet by an equality join; their month intervals are
    intersected. A gram that no edit touches is one row for all months.
    """
    one = intervals.select("topic_id", "pos", F.col("token").alias("c"), "valid_from", "valid_to")
    none = F.lit(None).cast("string")
    if order == 1:
        return one.select("topic_id", "pos", none.alias("a"), none.alias("b"), "c", "valid_from", "valid_to")

    def before(left: DataFrame, names: dict[str, str], back: int) -> DataFrame:
        prev = intervals.select("topic_id", (F.col("pos") + back).alias("pos"), F.col("token").alias("_t"), F.col("valid_from").alias("_f"), F.col("valid_to").alias("_u"))
        met = left.join(prev, ["topic_id", "pos"], "left").where("_f is null or (greatest(valid_from, _f) <= least(valid_to, _u))")
        return met.select("topic_id", "pos", *(F.col(x) for x in names if x in left.columns), F.col("_t").alias(next(n for n in names if n not in left.columns)), F.greatest("valid_from", "_f").alias("valid_from"), F.least("valid_to", "_u").alias("valid_to"))

    two = before(one, {"c": "", "b": ""}, 1)
    if order == 2:
        return two.select("topic_id", "pos", none.alias("a"), "b", "c", "valid_from", "valid_to")
    return before(two, {"b": "", "c": "", "a": ""}, 2).select("topic_id", "pos", "a", "b", "c", "valid_from", "valid_to")


def planted_weight(at: dict[int, int]) -> Column:
    """Copies of an interval's gram in a corpus that holds the versions of months ``at`` (month -> weight)."""
    return reduce(lambda x, y: x + y, [F.when((F.col("valid_from") <= m) & (F.lit(m) <= F.col("valid_to")), w).otherwise(0) for m, w in sorted(at.items())], F.lit(0)).cast("long")


class Model:
    """Counts of a union of weighted grams: ``counts`` by (a, b, c), ``totals`` of tokens, one column a mix."""

    def __init__(self, counts: DataFrame, totals: DataFrame, mixes: list[str]):
        self.counts, self.totals, self.mixes = counts, totals, mixes


def train(grams: DataFrame, mixes: list[str], only: DataFrame | None = None) -> Model:
    """A model for each weight column, in one pass over the grams. ``only`` holds the
    probes' grams: what no probe asks for becomes one row a task before the shuffle,
    whose size then follows the probes, and still counts towards the totals."""
    sums = [F.sum(m).alias(m) for m in mixes]
    kept = grams if only is None else _pruned(grams, only)
    counts = stored(kept.groupBy("a", "b", "c").agg(*sums))
    return Model(counts, counts.agg(*sums), mixes)


def _pruned(grams: DataFrame, only: DataFrame) -> DataFrame:
    """The grams with every part that no probe asks for set to null."""
    asked = stored(only.select("a", "b", "c").distinct())
    small = asked.count() <= BROADCAST_GRAMS
    as_is = F.broadcast if small else (lambda df: df)
    one = as_is(asked.select("c").distinct().withColumn("_1", F.lit(True)))
    two = as_is(asked.where("b is not null").select("b", "c").distinct().withColumn("_2", F.lit(True)))
    out = grams.join(one, "c", "left").join(two, ["b", "c"], "left")
    a = F.lit(None).cast("string")
    if not asked.where("a is not null").isEmpty():
        three = as_is(asked.where("a is not null").select("a", "b", "c").withColumn("_3", F.lit(True)))
        out, a = out.join(three, ["a", "b", "c"], "left"), F.when(F.col("_3"), F.col("a"))
    weights = [c for c in grams.columns if c not in ("a", "b", "c")]
    return out.select(a.alias("a"), F.when(F.col("_2"), F.col("b")).alias("b"), F.when(F.col("_1"), F.col("c")).alias("c"), *weights)


def score(model: Model, probes: DataFrame, order: int, lam: float = LAMBDA, vocabulary: int = VOCABULARY) -> DataFrame:
    """The probes' rows with ln p of their token under each mix (columns lp_<mix>)."""
    mixes = model.mixes

    def level(keys: list[str], where: str | None, tag: str, rename: dict[str, str]) -> DataFrame:
        src = model.counts.where(where) if where else model.counts
        out = src.groupBy(*keys).agg(*(F.sum(m).alias(f"{tag}_{m}") for m in mixes))
        return reduce(lambda d, kv: d.withColumnRenamed(*kv), rename.items(), out)

    out = probes.join(level(["c"], None, "n1", {}), "c", "left")
    if order >= 2:
        out = out.join(level(["b", "c"], "b is not null", "n2", {}), ["b", "c"], "left")
        out = out.join(level(["c"], None, "h1", {"c": "b"}), "b", "left")
    if order >= 3:
        out = out.join(level(["a", "b", "c"], "a is not null", "n3", {}), ["a", "b", "c"], "left")
        out = out.join(level(["b", "c"], "b is not null", "h2", {"b": "a", "c": "b"}), ["a", "b"], "left")
    totals = model.totals.select(*(F.col(m).alias(f"total_{m}") for m in mixes))
    out = out.join(F.broadcast(totals))  # one row
    for m in mixes:
        n = lambda tag: F.coalesce(F.col(f"{tag}_{m}"), F.lit(0)).cast("double")  # noqa: E731, B023
        p = (n("n1") + 1) / (F.col(f"total_{m}") + vocabulary)
        for k in range(2, order + 1):
            p = F.when(n(f"h{k - 1}") > 0, lam * n(f"n{k}") / n(f"h{k - 1}") + (1 - lam) * p).otherwise(p)
        out = out.withColumn(f"lp_{m}", F.log(p))
    drop = [f"{t}_{m}" for t in ("n1", "n2", "n3", "h1", "h2", "total") for m in mixes]
    return out.drop(*drop)


def unpivot_mixes(df: DataFrame, keys: list[str], mixes: list[str], prefix: str, value: str) -> DataFrame:
    """One row a mix: (model, keys..., value)."""
    pairs = F.explode(F.array(*(F.struct(F.lit(m).alias("model"), F.col(f"{prefix}{m}").alias(value)) for m in mixes)))
    return df.select(*keys, pairs.alias("_m")).select("_m.model", *keys, f"_m.{value}")


def monthly_perplexity(scored: DataFrame, grid: DataFrame, mixes: list[str]) -> DataFrame:
    """(model, topic_id, month_ix, ppl) from grams scored as intervals.

    Sums change only where an interval begins or ends, so differences are summed
    per topic and month and accumulated along the grid.
    """
    lps = [f"lp_{m}" for m in mixes]
    begin = scored.select("topic_id", F.col("valid_from").alias("m"), *lps, F.lit(1).alias("n"))
    end = scored.select("topic_id", (F.col("valid_to") + 1).alias("m"), *((-F.col(x)).alias(x) for x in lps), F.lit(-1).alias("n"))
    steps = begin.union(end).groupBy("topic_id", "m").agg(*(F.sum(x).alias(x) for x in lps), F.sum("n").alias("n"))
    packed = steps.groupBy("topic_id").agg(F.collect_list(F.struct("m", *lps, "n")).alias("steps"))
    at = packed.join(F.broadcast(grid))  # the calendar's months for each topic
    upto = F.filter("steps", lambda s: s["m"] <= F.col("month_ix"))
    def total(x: str) -> Column:
        return F.aggregate(upto, F.lit(0.0), lambda acc, s: acc + s[x])

    sums = {x: total(x) for x in lps}
    n = F.aggregate(upto, F.lit(0).cast("long"), lambda acc, s: acc + s["n"])
    out = at.select("topic_id", "month_ix", n.alias("n"), *(v.alias(k) for k, v in sums.items()))
    out = out.select("topic_id", "month_ix", *(F.exp(-F.col(x) / F.col("n")).alias(f"ppl_{m}") for x, m in zip(lps, mixes, strict=True)))
    return unpivot_mixes(out, ["topic_id", "month_ix"], mixes, "ppl_", "ppl")
