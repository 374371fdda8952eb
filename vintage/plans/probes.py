"""Probe sets: one topic in many dated versions, or dated documents by month.

A version differs from the month before in a few words, so versions are kept as
word intervals: (topic, position, token, first month, last month). All months
together cost a row for each base word and two for each edit; months are only
expanded where a method needs a row per month.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import tokens
from ..functions.timegrid import LAST_MONTH, month_ix, months


def edit_log(orders: DataFrame, lineitem: DataFrame) -> DataFrame:
    """(topic_id, month_ix, major, minor, payload): one edit a line."""
    heads = orders.select(F.col("o_orderkey").alias("major"), F.col("o_custkey").alias("topic_id"), month_ix(F.col("o_orderdate")).alias("month_ix"))
    lines = lineitem.select(F.col("l_orderkey").alias("major"), F.col("l_linenumber").cast("long").alias("minor"), F.col("l_partkey").alias("payload"))
    return heads.join(lines, "major").select("topic_id", "month_ix", "major", "minor", "payload")


def existing_since(edits: DataFrame, month: int = 5) -> DataFrame:
    """Edits of topics that had a version at the start of the grid."""
    old = edits.groupBy("topic_id").agg(F.min("month_ix").alias("_first")).where(F.col("_first") <= month)
    return edits.join(old.select("topic_id"), "topic_id", "left_semi")


def top_edited(edits: DataFrame, k: int = 5000) -> DataFrame:
    """(topic_id, n_edits) of the k most edited topics, ties by id."""
    return edits.groupBy("topic_id").agg(F.count(F.lit(1)).alias("n_edits")).orderBy(F.desc("n_edits"), "topic_id").limit(k)


def topics(documents: DataFrame, edits: DataFrame, k: int = 5000, least_words: int = 100, start: int = 5) -> DataFrame:
    """The topics probed: long enough, there from the start, most edited first."""
    counted = edits.groupBy("topic_id").agg(F.count(F.lit(1)).alias("n_edits"), F.min("month_ix").alias("first_month")).where(F.col("first_month") <= start)
    long = documents.where(F.size(tokens(F.col("text"))) >= least_words).select(F.col("doc_id").alias("topic_id"))
    return counted.join(long, "topic_id", "left_semi").orderBy(F.desc("n_edits"), "topic_id").limit(k)


def _bases(documents: DataFrame, chosen: DataFrame, n_tokens: int) -> DataFrame:
    """(topic_id, toks, tail): the chosen topics' first words, and the text behind them (empty without any)."""
    words = documents.join(chosen.select(F.col("topic_id").alias("doc_id")), "doc_id").select(F.col("doc_id").alias("topic_id"), tokens(F.col("text")).alias("_all"))
    return words.select("topic_id", F.slice("_all", 1, n_tokens).alias("toks"), F.array_join(F.slice("_all", F.lit(n_tokens + 1), F.greatest(F.size("_all"), F.lit(1))), " ").alias("tail"))


def _last_edits(edits: DataFrame, sizes: DataFrame) -> DataFrame:
    """(topic_id, pos, month_ix, token): the last edit of a word within a month. ``sizes``: (topic_id, n)."""
    hits = edits.join(sizes, "topic_id").select("topic_id", "month_ix", ((F.col("major") * 31 + F.col("minor") * 97) % F.col("n")).cast("int").alias("pos"), F.concat(F.lit("p"), F.col("payload").cast("string")).alias("token"), F.struct("major", "minor", "payload").alias("at"))
    return hits.groupBy("topic_id", "pos", "month_ix").agg(F.max_by("token", "at").alias("token"))


def evolving_set(documents: DataFrame, edits: DataFrame, chosen: DataFrame, n_tokens: int = 512) -> DataFrame:
    """Word intervals (topic_id, pos, token, valid_from, valid_to) of the chosen topics."""
    base = _bases(documents, chosen, n_tokens)
    last = _last_edits(edits, base.select("topic_id", F.size("toks").alias("n")))
    words = base.select("topic_id", F.posexplode("toks").alias("pos", "token"))
    states = words.select("topic_id", "pos", F.lit(0).alias("valid_from"), F.lit(0).alias("edited"), "token").union(last.select("topic_id", "pos", "month_ix", F.lit(1), "token"))
    w = Window.partitionBy("topic_id", "pos").orderBy("valid_from", "edited")
    until = F.coalesce(F.lead("valid_from").over(w) - 1, F.lit(LAST_MONTH))
    return states.withColumn("valid_to", until).where("valid_from <= valid_to").select("topic_id", "pos", "token", "valid_from", "valid_to")


def packed_set(documents: DataFrame, edits: DataFrame, chosen: DataFrame, n_tokens: int = 512) -> DataFrame:
    """(topic_id, toks, tail, edits): a topic's whole history in one row.

    ``toks`` are the first words before any edit, ``tail`` the text behind them,
    which no edit reaches, ``edits`` the (month, pos, token) in order of months.
    All versions together are so little longer than one of them.
    """
    base = _bases(documents, chosen, n_tokens)
    last = _last_edits(edits, base.select("topic_id", F.size("toks").alias("n")))
    log = last.groupBy("topic_id").agg(F.array_sort(F.collect_list(F.struct(F.col("month_ix").alias("month"), "pos", "token"))).alias("edits"))
    none = F.array().cast("array<struct<month:int,pos:int,token:string>>")
    return base.join(log, "topic_id", "left").withColumn("edits", F.coalesce("edits", none))


def words_at(month: Column) -> Column:
    """A packed topic's first words as they stood at the end of a month."""
    done = F.filter("edits", lambda e: e["month"] <= month)
    return F.aggregate(done, F.col("toks"), lambda w, e: F.concat(F.slice(w, F.lit(1), e["pos"]), F.array(e["token"]), F.slice(w, e["pos"] + 2, F.size(w))))


def text_at(month: Column) -> Column:
    """A packed topic's whole text as it stood at the end of a month."""
    return F.array_join(F.concat(words_at(month), F.when(F.col("tail") != "", F.array("tail")).otherwise(F.array().cast("array<string>"))), " ")


def packed_versions(packed: DataFrame) -> DataFrame:
    """The packed topics once for each distinct version, with version_from and version_to."""
    starts = F.array_sort(F.array_union(F.array(F.lit(0)), F.transform("edits", lambda e: e["month"])))
    until = F.concat(F.transform(F.slice("_starts", F.lit(2), F.size("_starts")), lambda m: m - 1), F.array(F.lit(LAST_MONTH)))
    spans = packed.withColumn("_starts", starts).withColumn("_spans", F.arrays_zip(F.col("_starts").alias("f"), until.alias("t")))
    return spans.select(*packed.columns, F.explode("_spans").alias("_s")).select(*packed.columns, F.col("_s.f").alias("version_from"), F.col("_s.t").alias("version_to"))


def whole_versions(packed: DataFrame) -> DataFrame:
    """(topic_id, version_from, version_to, text): each distinct version written out, to the end."""
    return packed_versions(packed).select("topic_id", "version_from", "version_to", text_at(F.col("version_from")).alias("text"))


def version_intervals(intervals: DataFrame) -> DataFrame:
    """(topic_id, version_from, version_to): spans of months without a change; the month 0 always begins one."""
    starts = intervals.select("topic_id", F.col("valid_from").alias("version_from")).union(intervals.select("topic_id", F.lit(0))).distinct()
    until = F.coalesce(F.lead("version_from").over(Window.partitionBy("topic_id").orderBy("version_from")) - 1, F.lit(LAST_MONTH))
    return starts.withColumn("version_to", until)


def version_texts(intervals: DataFrame, versions: DataFrame | None = None) -> DataFrame:
    """(topic_id, version_from, version_to, text): each distinct version written out."""
    spans = version_intervals(intervals) if versions is None else versions
    met = spans.join(intervals, "topic_id").where("valid_from <= version_from and version_from <= valid_to")
    words = F.array_sort(F.collect_list(F.struct("pos", "token")))
    return met.groupBy("topic_id", "version_from", "version_to").agg(F.array_join(F.transform(words, lambda x: x["token"]), " ").alias("text"))


def at_months(intervals: DataFrame, at: list[int]) -> DataFrame:
    """(topic_id, month_ix, pos, token) of the versions at the given months."""
    return intervals.withColumn("month_ix", F.explode(F.array(*map(F.lit, at)))).where("valid_from <= month_ix and month_ix <= valid_to").select("topic_id", "month_ix", "pos", "token")


def dated_set(documents: DataFrame, orders: DataFrame, per_bucket: int = 500, seed: str = "dt") -> DataFrame:
    """(doc_id, month_ix, text): at most ``per_bucket`` dated documents a month, picked by a hash of the id."""
    dated = documents.join(orders.select(F.col("o_orderkey").alias("doc_id"), month_ix(F.col("o_orderdate")).alias("month_ix")), "doc_id")
    order = F.md5(F.concat(F.lit(seed), F.col("doc_id").cast("string")).cast("binary"))
    ranked = dated.withColumn("_rank", F.row_number().over(Window.partitionBy("month_ix").orderBy(order, "doc_id")))
    return ranked.where(F.col("_rank") <= per_bucket).select("doc_id", "month_ix", "text")


def static_set(items: DataFrame, spark, id_col: str = "item_id") -> DataFrame:
    """A resource that never changes, as intervals over the whole grid: the control."""
    return items.select(F.col(id_col).alias("topic_id"), F.posexplode(tokens(F.col("text"))).alias("pos", "token")).select("topic_id", "pos", "token", F.lit(0).alias("valid_from"), F.lit(LAST_MONTH).alias("valid_to"))


def month_grid(spark, step: int = 1) -> DataFrame:
    return months(spark, LAST_MONTH, step)
