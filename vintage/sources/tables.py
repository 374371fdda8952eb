"""Reading the given tables, pages and urls; scratch tables in the shared folder."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_OWN: list[str] = []
#: Scratch tables written and not yet released.
_SCRATCH: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; unset, a temporary folder on one machine and the warehouse on several."""
    if named := spark.conf.get("spark.checkpoint.dir", None):
        return named.rstrip("/")
    if spark.sparkContext.master.split("[")[0] == "local":
        if not _OWN:
            _OWN.append(tempfile.mkdtemp(prefix="vintage-"))
            atexit.register(shutil.rmtree, _OWN[0], ignore_errors=True)
        return f"file://{_OWN[0]}"
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/")


def stored(df: DataFrame, *partition_by: str) -> DataFrame:
    """Written to the shared folder and read back: lineage ends there, and several readers share one computation.

    A lost executor then costs a file read, not the work before it. ``release``
    deletes such tables once their readers are done.
    """
    path = f"{shared_dir(df.sparkSession)}/stored-{uuid.uuid4().hex}"
    _SCRATCH.append(path)
    writer = df.write.option("compression", "zstd")
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def delete(spark: SparkSession, path: str) -> None:
    """Deletes a folder by Spark's own file system, wherever that is."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def release(spark: SparkSession, since: int = 0) -> int:
    """Deletes the scratch tables written after the first ``since``; DataFrames that read them end with that.

    ``len(scratch())`` before a query, given here after its result is written,
    deletes that query's tables alone. Returns how many went.
    """
    gone = _SCRATCH[since:]
    for path in gone:
        delete(spark, path)
    del _SCRATCH[since:]
    return len(gone)


def scratch() -> tuple[str, ...]:
    return tuple(_SCRATCH)


def write_bucketed(df: DataFrame, name: str, buckets: int, *columns: str) -> None:
    """A table bucketed by its join columns, so that later joins on them don't shuffle it."""
    df.write.bucketBy(buckets, *columns).sortBy(*columns).mode("overwrite").saveAsTable(name)


def host_of(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, r"://([^/?#:]+)", 1))


def is_under(host: Column, suffixes: list[str]) -> Column:
    """True where a host is one of the domains or below one."""
    hit = F.lit(False)
    for s in suffixes:
        hit = hit | (host == s) | host.endswith("." + s)
    return hit


def text_of_html(html: Column) -> Column:
    """Readable text: scripts, styles, comments and tags go, common entities come back, spaces collapse."""
    out = F.regexp_replace(html, r"(?is)<script[^>]*>.*?</script>|<style[^>]*>.*?</style>|<!--.*?-->", " ")
    out = F.regexp_replace(F.regexp_replace(out, r"(?i)<br>|</p>|</h1>|</li>", "\n"), r"<[^>]*>", " ")
    for name, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&copy;", "©"), ("&middot;", "·"), ("&nbsp;", " "), ("&amp;", "&")):
        out = F.replace(out, F.lit(name), F.lit(char))
    return F.trim(F.regexp_replace(F.regexp_replace(out, r"[ \t]+", " "), r" ?\n[ \n]*", "\n"))
