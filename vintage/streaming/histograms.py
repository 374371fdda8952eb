"""Histograms and copies kept fresh as events arrive."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.joins import checked_broadcast

LATE = "1 hour"


def tumbling(events: DataFrame, size: str = "1 day", late: str = LATE) -> DataFrame:
    """(start, event_type, n) per window; works on batches and streams alike."""
    out = _marked(events, late).groupBy(F.window("ts", size), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return out.select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, size: str = "2 days", every: str = "1 day", late: str = LATE) -> DataFrame:
    out = _marked(events, late).groupBy(F.window("ts", size, every)).agg(F.count(F.lit(1)).alias("n"))
    return out.select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "6 hours", late: str = LATE) -> DataFrame:
    """(user_id, start, end, n): runs of a user's events without a gap."""
    out = _marked(events, late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return out.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def distinct_copies(events: DataFrame, keys: list[str], late: str = LATE) -> DataFrame:
    """The first of each key within the watermark, on a stream; over all, on a batch."""
    return _marked(events, late).dropDuplicatesWithinWatermark(keys) if events.isStreaming else events.dropDuplicates(keys)


def with_static(docs: DataFrame, known: DataFrame, key: str) -> DataFrame:
    """Arriving documents that match a static table of known hashes or terms, which is broadcast if it is small."""
    return docs.join(checked_broadcast(known), key)


def late_rows(query: StreamingQuery) -> int:
    """Rows that came behind the watermark and so are in no window, over the batches the query still remembers."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])


def edits_meet_crawls(edits: DataFrame, crawls: DataFrame, within: str = "7 days", late: str = LATE) -> DataFrame:
    """Stream-stream interval join: crawls of a topic within some days behind an edit."""
    e = edits.select("topic_id", F.col("ts").alias("edit_ts")).withWatermark("edit_ts", late) if edits.isStreaming else edits.select("topic_id", F.col("ts").alias("edit_ts"))
    c = crawls.select(F.col("topic_id").alias("crawled"), F.col("ts").alias("crawl_ts"))
    c = c.withWatermark("crawl_ts", late) if crawls.isStreaming else c
    return e.join(c, (F.col("topic_id") == F.col("crawled")) & (F.col("crawl_ts") >= F.col("edit_ts")) & (F.col("crawl_ts") <= F.col("edit_ts") + F.expr(f"INTERVAL {within}")))


def nearest_months(matches: DataFrame) -> DataFrame:
    """Running best distance and its months for each document, as matches (doc_id, month_ix, dist) arrive."""
    def step(key: tuple, pdfs: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        best, months = state.get if state.exists else (None, "")
        have = {int(m) for m in months.split(",") if m}
        for pdf in pdfs:
            low = int(pdf["dist"].min())
            if best is None or low < best:
                best, have = low, set()
            if low == best:
                have |= {int(m) for m in pdf.loc[pdf["dist"] == low, "month_ix"]}
        text = ",".join(map(str, sorted(have)))
        state.update((best, text))
        yield pd.DataFrame({"doc_id": [key[0]], "dist": [best], "months": [text]})

    return matches.groupBy("doc_id").applyInPandasWithState(step, "doc_id long, dist int, months string", "dist int, months string", "update", GroupStateTimeout.NoTimeout)


def add_counts(path: str):
    """A foreachBatch sink that keeps additive counts (keys..., n) as one Parquet row group a batch.

    Counts of n-grams add up, so a batch is appended under its number and
    rewritten if it is repeated; readers sum over batches.
    """
    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write


def _marked(events: DataFrame, late: str) -> DataFrame:
    return events.withWatermark("ts", late) if events.isStreaming else events
