"""Comparing cutoffs with stated dates, and curves with histograms."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def cards(spark: SparkSession, stated: dict[str, int | None]) -> DataFrame:
    """Model cards: (model, stated), null where a date isn't known."""
    return spark.createDataFrame(list(stated.items()), "model string, stated int")


def gap(effective: DataFrame, model_cards: DataFrame) -> DataFrame:
    """(model, cutoff, stated, gap in months); the gap is null where nothing is stated."""
    return effective.join(F.broadcast(model_cards), "model").select("model", "cutoff", "stated", (F.col("cutoff") - F.col("stated")).alias("gap"))


def _ranks(df: DataFrame, col: str) -> Column:
    w = Window.partitionBy("model").orderBy(col)
    same = Window.partitionBy("model", col)
    return F.rank().over(w) + (F.count(F.lit(1)).over(same) - 1) / 2.0


def curve_vs_hist(curve: DataFrame, hist: DataFrame) -> DataFrame:
    """(model, pearson, spearman) of relative perplexity and version counts over months; both expected below 0."""
    met = curve.select("model", "month_ix", "rel").join(hist.select("model", "month_ix", "n"), ["model", "month_ix"])
    met = met.withColumn("rr", _ranks(met, "rel")).withColumn("rn", _ranks(met, "n"))
    return met.groupBy("model").agg(F.corr("rel", "n").alias("pearson"), F.corr("rr", "rn").alias("spearman"))


def agreement(one: DataFrame, other: DataFrame) -> DataFrame:
    """How far two attributions (topic_id, doc_id, months) agree: documents in both, and with a month in common."""
    met = one.select("topic_id", "doc_id", F.col("months").alias("m1")).join(other.select("topic_id", "doc_id", F.col("months").alias("m2")), ["topic_id", "doc_id"], "full")
    return met.agg(F.count(F.lit(1)).alias("either"), F.count_if(F.col("m1").isNotNull() & F.col("m2").isNotNull()).alias("both"), F.count_if(F.arrays_overlap("m1", "m2")).alias("same_month"))
