"""From perplexities to curves and effective cutoffs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def trimmed_mean(ppl: DataFrame, trim: float = 0.025, approx: bool = False, agg: str = "trimmed", item: str = "topic_id") -> DataFrame:
    """(model, month_ix, ppl, n): mean over a month's items without floor(trim * n) at either end.

    ``approx`` replaces the ranking by a first pass of percentile bounds, for
    months of very many items; ``agg`` may be ``mean`` or ``median`` instead.
    """
    keys = ["model", "month_ix"]
    if agg == "mean":
        return ppl.groupBy(*keys).agg(F.avg("ppl").alias("ppl"), F.count(F.lit(1)).alias("n"))
    if agg == "median":
        return ppl.groupBy(*keys).agg(F.percentile("ppl", F.lit(0.5)).alias("ppl"), F.count(F.lit(1)).alias("n"))
    if approx:
        bounds = ppl.groupBy(*keys).agg(F.percentile_approx("ppl", F.array(F.lit(trim), F.lit(1 - trim)), 10_000).alias("b"))
        kept = ppl.join(F.broadcast(bounds), keys).where(F.col("ppl").between(F.col("b")[0], F.col("b")[1]))
        return kept.groupBy(*keys).agg(F.avg("ppl").alias("ppl"), F.count(F.lit(1)).alias("n"))
    rank = F.row_number().over(Window.partitionBy(*keys).orderBy("ppl", item))
    size = F.count(F.lit(1)).over(Window.partitionBy(*keys))
    ranked = ppl.select(*keys, "ppl", rank.alias("r"), size.alias("n")).withColumn("k", F.floor(F.col("n") * trim))
    return ranked.where("k < r and r <= n - k").groupBy(*keys).agg(F.avg("ppl").alias("ppl"), F.count(F.lit(1)).alias("n"))


def absolute(ppl: DataFrame) -> DataFrame:
    """Plain mean perplexity a month, unscaled."""
    return trimmed_mean(ppl, agg="mean")


def single_topic(ppl: DataFrame, topic_id: int) -> DataFrame:
    """One document's own curve."""
    return ppl.where(F.col("topic_id") == topic_id).select("model", "month_ix", "ppl")


def relative(curve: DataFrame) -> DataFrame:
    """The curve with ``rel``, scaled to 0..1 over the whole span; null where it is flat."""
    w = Window.partitionBy("model")
    low, high = F.min("ppl").over(w), F.max("ppl").over(w)
    return curve.withColumn("rel", (F.col("ppl") - low) / F.nullif(high - low, F.lit(0.0)))


def effective_cutoff(curve: DataFrame, rule: str = "argmin") -> DataFrame:
    """(model, cutoff). ``argmin``: the month of least relative perplexity, earliest on ties.
    ``rise``: the last month before the split into low and high that leaves least squares."""
    if rule == "argmin":
        return curve.where("rel is not null").groupBy("model").agg(F.min_by("month_ix", F.struct("rel", "month_ix")).alias("cutoff"))
    w = Window.partitionBy("model").orderBy("month_ix").rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy("model")
    s = curve.select("model", "month_ix", F.count("rel").over(w).alias("n1"), F.sum("rel").over(w).alias("s1"), F.count("rel").over(whole).alias("n"), F.sum("rel").over(whole).alias("s"))
    s = s.where("n1 < n").withColumn("m1", F.col("s1") / F.col("n1")).withColumn("m2", (F.col("s") - F.col("s1")) / (F.col("n") - F.col("n1")))
    s = s.where("m2 > m1").withColumn("gain", F.col("n1") * (F.col("n") - F.col("n1")) / F.col("n") * (F.col("m2") - F.col("m1")) * (F.col("m2") - F.col("m1")))
    return s.groupBy("model").agg(F.max_by("month_ix", F.struct("gain", -F.col("month_ix"))).alias("cutoff"))


def cutoff_spread(curve: DataFrame, tau: float = 0.05) -> DataFrame:
    """(model, months within tau, weights): the cutoff as a distribution, weights going with exp(-rel / tau)."""
    w = F.exp(-F.col("rel") / tau)
    share = curve.where("rel is not null").withColumn("weight", w / F.sum(w).over(Window.partitionBy("model")))
    return share.groupBy("model").agg(F.array_sort(F.collect_list(F.when(F.col("rel") <= tau, F.col("month_ix")))).alias("months"), F.array_sort(F.collect_list(F.struct("month_ix", "weight"))).alias("weights"))


def sharpness(curve: DataFrame, tau: float = 0.05) -> DataFrame:
    """(model, width): number of months within tau of the minimum."""
    return curve.groupBy("model").agg(F.count_if(F.col("rel") <= tau).alias("width"))
