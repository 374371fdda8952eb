"""Ablations: how cutoffs hold when models or probe sets shrink."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .curves import effective_cutoff


def union(parts: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), parts)


def ranked_topics(topics: DataFrame) -> DataFrame:
    """(topic_id, rank by edits). At most the number of topics asked for, so one window may hold them."""
    return topics.select("topic_id", F.row_number().over(Window.orderBy(F.desc("n_edits"), "topic_id")).alias("rank"))


def by_size(ppl: DataFrame, ranked: DataFrame, sizes: list[int], full: int = 5000) -> DataFrame:
    """Perplexities once for each nested set of the first x topics; the model's name carries x."""
    sized = F.explode(F.filter(F.array(*map(F.lit, [full, *sizes])), lambda x: F.col("rank") <= x))
    met = ppl.join(ranked, "topic_id").withColumn("x", sized)
    return met.select(F.concat_ws("_", "model", F.col("x").cast("string")).alias("model"), "topic_id", "month_ix", "ppl")


def summary(curve: DataFrame) -> DataFrame:
    """(model, cutoff, width, deviation): where the minimum lies, how wide it is, how much the curve varies."""
    stats = curve.groupBy("model").agg(F.count_if(F.col("rel") <= 0.05).alias("width"), F.round(F.stddev("rel"), 4).alias("deviation"))
    return effective_cutoff(curve).join(stats, "model")


def stability(summaries: DataFrame, reference: str) -> DataFrame:
    """(family, max_shift, mean_deviation): how far the cutoff moves from the reference setting, how much curves vary.

    A model's name ends in its setting behind the last underscore; the rest is its family.
    """
    named = summaries.select("cutoff", "deviation", F.regexp_extract("model", "^(.*)_([^_]*)$", 1).alias("family"), F.regexp_extract("model", "^(.*)_([^_]*)$", 2).alias("setting"))
    ref = named.where(F.col("setting") == reference).select("family", F.col("cutoff").alias("_ref"))
    return named.join(F.broadcast(ref), "family").groupBy("family").agg(F.max(F.abs(F.col("cutoff") - F.col("_ref"))).alias("max_shift"), F.round(F.avg("deviation"), 4).alias("mean_deviation"))
