"""What a run costs: seconds and bytes written to shuffles."""

from __future__ import annotations

import time
from typing import NamedTuple

from pyspark.sql import DataFrame, SparkSession


class Cost(NamedTuple):
    seconds: float
    shuffle_bytes: int


def shuffle_bytes(spark: SparkSession) -> int:
    """Bytes that all executors have written to shuffles since the session began."""
    listed = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(int(listed.apply(k).totalShuffleWrite()) for k in range(listed.size()))


def run_cost(make, spark: SparkSession) -> Cost:
    """The cost of building a DataFrame with ``make`` and working out all its rows."""
    before, began = shuffle_bytes(spark), time.perf_counter()
    df: DataFrame = make()
    df.write.format("noop").mode("overwrite").save()
    seconds = time.perf_counter() - began
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    return Cost(seconds, shuffle_bytes(spark) - before)
