"""Monthly buckets: months since the first month of the grid."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The dates of the given tables run over these months.
FIRST_YEAR, LAST_MONTH = 1995, 79


def month_ix(date: Column, first_year: int = FIRST_YEAR) -> Column:
    return ((F.year(date) - first_year) * 12 + F.month(date) - 1).cast("int")


def month_date(ix: Column, first_year: int = FIRST_YEAR) -> Column:
    return F.add_months(F.make_date(F.lit(first_year), F.lit(1), F.lit(1)), ix)


def months(spark: SparkSession, last: int = LAST_MONTH, step: int = 1) -> DataFrame:
    """The grid, one row a month; its size is that of the calendar, not of the data."""
    return spark.range(0, last + 1, step, 1).select(F.col("id").cast("int").alias("month_ix"))
