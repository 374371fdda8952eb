"""Joins the methods need beyond the built-in ones, and the built-in ones by name."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Rows of a side that may be broadcast or crossed without further ado.
SMALL = 1_000_000


def checked_broadcast(df: DataFrame, most: int = SMALL) -> DataFrame:
    """The side with a broadcast hint if it has at most ``most`` rows; as it is otherwise."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def checked_cross(big: DataFrame, small: DataFrame, most: int = 10_000) -> DataFrame:
    """Every row beside every row of a side that must be small: a calendar, a grid, a few bounds."""
    if small.limit(most + 1).count() > most:
        raise ValueError(f"the small side of a cross join has more than {most} rows")
    return big.crossJoin(F.broadcast(small))


def interval_join(points: DataFrame, spans: DataFrame, key: list[str], point: str, start: str, end: str, width: int) -> DataFrame:
    """Points inside spans of one key, as an equality join on buckets of ``width``.

    A span is listed in each bucket it touches, so no key's points meet all its
    spans; the exact test follows.
    """
    p = points.withColumn("_bucket", F.floor(F.col(point) / width))
    s = spans.withColumn("_bucket", F.explode(F.sequence(F.floor(F.col(start) / width), F.floor(F.col(end) / width))))
    return p.join(s, [*key, "_bucket"]).where((F.col(start) <= F.col(point)) & (F.col(point) <= F.col(end))).drop("_bucket")


def asof_join(left: DataFrame, right: DataFrame, key: list[str], when: str, value: list[str]) -> DataFrame:
    """Each left row with the latest right values at or before it, by one union and one window.

    Equal times count as before. ``right`` must be ordered by ``when`` alone;
    ties among its rows are settled by the values.
    """
    l = left.select(*left.columns, *(F.lit(None).cast(dict(right.dtypes)[v]).alias(v) for v in value), F.lit(1).alias("_left"))  # noqa: E741
    r = right.select(*(F.col(c) if c in (*key, when) else F.lit(None).cast(t).alias(c) for c, t in left.dtypes), *value, F.lit(0).alias("_left"))
    w = Window.partitionBy(*key).orderBy(when, "_left", *value).rowsBetween(Window.unboundedPreceding, 0)
    both = l.unionByName(r)
    filled = both.select(*left.columns, "_left", *(F.last(v, ignorenulls=True).over(w).alias(v) for v in value))
    return filled.where("_left = 1").drop("_left")


def row_salt(df: DataFrame, salts: int) -> Column:
    """A number below ``salts`` from a row's values and its partition, never from its place there.

    A task that runs again after a lost executor deals its rows as before, in
    whatever order they come. Equal rows of one partition share a number.
    """
    hashable = [F.col(f"`{f.name}`") for f in df.schema.fields if not any(k in f.dataType.simpleString() for k in ("map<", "variant"))]
    return F.pmod(F.xxhash64(F.spark_partition_id(), *hashable), F.lit(salts)).cast("int")


def salted_join(big: DataFrame, other: DataFrame, key: str, salts: int, how: str = "inner") -> DataFrame:
    """A join whose hot keys are spread over ``salts`` tasks; the other side is repeated as often.

    So ``how`` may keep unmatched rows of the big side only.
    """
    if how.lower().startswith(("right", "full", "outer")):
        raise ValueError(f"a salted join can't keep unmatched rows of the repeated side: {how}")
    b = big.withColumn("_salt", row_salt(big, salts))
    o = other.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return b.join(o, [key, "_salt"], how).drop("_salt")


def salted_count(df: DataFrame, keys: list[str], salts: int = 16) -> DataFrame:
    """Counts in two steps, the first salted by partition, so a task still hands on one row a key."""
    first = df.groupBy(*keys, F.pmod(F.spark_partition_id(), F.lit(salts)).alias("_salt")).agg(F.count(F.lit(1)).alias("n"))
    return first.groupBy(*keys).agg(F.sum("n").alias("n"))


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two arrays in double precision."""
    def dot(x: Column, y: Column) -> Column:
        return F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)

    return dot(a, b) / F.nullif(F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)), F.lit(0.0))
