"""Fuzzy dedup: documents joined where the Jaccard similarity of their word shingles is confirmed.

Equal texts are one before anything else. Min-hashes of a text's shingles form
bands; texts that share a band are candidates. At a similarity of 0.8, 24 bands of
four miss a pair with a chance of 3e-6; ``bands`` sets that. Candidates of a
bucket are first compared with its least member. Buckets that this leaves in
several components, of more than two members, are then compared across components
block by block, so no link between components is lost and a large family of
copies costs one comparison a member. Blocks are bounded by rows and by hashes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import canonical, runs_of, tokens
from ..operators.components import connected_components
from ..sources.tables import stored

WORDS, ROWS = 5, 4
#: Members a block holds at most, and hashes; a longer set makes a block by itself.
BLOCK, BLOCK_HASHES = 256, 1 << 20


def shingle_hashes(text: Column, n: int = WORDS) -> Column:
    """Distinct hashes of runs of n words; the whole sequence as one below n words, none without words."""
    words = tokens(text)
    runs = runs_of(words, n, lambda ws: F.xxhash64(*ws))
    return F.when(F.size(words) >= n, F.array_distinct(runs)).when(F.size(words) > 0, F.array(F.xxhash64(canonical(text)))).otherwise(F.array().cast("array<bigint>"))


def _buckets(sets: DataFrame, bands: int) -> DataFrame:
    """(digest, bucket) for each band of each non-empty set."""
    rng = np.random.default_rng(7)
    times = rng.integers(0, 1 << 63, bands * ROWS, dtype=np.uint64) | np.uint64(1)
    mixer = rng.integers(0, 1 << 63, (bands, ROWS), dtype=np.uint64) | np.uint64(1)
    salt = np.arange(1, bands + 1, dtype=np.uint64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, BLOCK):
                b = whole.slice(lo, BLOCK)
                sizes = b.column("grams").value_lengths().to_numpy()
                x = b.column("grams").flatten().to_numpy().view(np.uint64)
                at = np.concatenate([[0], np.cumsum(sizes)[:-1]])
                least = np.empty((b.num_rows, bands * ROWS), np.uint64)
                for k, t in enumerate(times):
                    h = x * t
                    least[:, k] = np.minimum.reduceat(h ^ (h >> np.uint64(29)), at)
                key = ((least.reshape(-1, bands, ROWS) * mixer).sum(axis=2, dtype=np.uint64) ^ salt) * np.uint64(0x9E3779B97F4A7C15)
                yield pa.RecordBatch.from_arrays([b.column("digest"), pa.array(key.view(np.int64).tolist(), pa.list_(pa.int64()))], ["digest", "buckets"])

    found = sets.where(F.size("grams") > 0).select("digest", "grams").mapInArrow(run, "digest string, buckets array<bigint>")
    return found.select("digest", F.explode("buckets").alias("bucket"))


def _alike(x: Column, y: Column, percent: int) -> Column:
    both = F.size(F.array_intersect(x, y))
    return 100 * both >= percent * (F.size(x) + F.size(y) - both)


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    one = pairs.join(sets.select(F.col("digest").alias("a"), F.col("grams").alias("x")), "a")
    two = one.join(sets.select(F.col("digest").alias("b"), F.col("grams").alias("y")), "b")
    return two.where(_alike(F.col("x"), F.col("y"), percent)).select("a", "b")


def _across(placed: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links between members of one bucket that stand in different components.

    Members are dealt to blocks; a group is one pair of blocks, so no bucket is
    ever one task's, whatever its size.
    """
    load = sets.select("digest", F.size("grams").alias("hashes"))
    sized = placed.join(load, "digest")
    per = sized.groupBy("bucket").agg(F.greatest(F.ceil(F.count(F.lit(1)) / BLOCK), F.ceil(F.sum("hashes") / BLOCK_HASHES)).cast("int").alias("blocks"))
    dealt = sized.join(per, "bucket").withColumn("mine", F.pmod(F.xxhash64("digest"), "blocks").cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("bucket", "digest", "part", "mine", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j")).join(sets.select("digest", "grams"), "digest")

    def run(t: pa.Table) -> pa.Table:
        i, j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
        mine, digest, part = (t.column(c).to_pylist() for c in ("mine", "digest", "part"))
        grams = [np.sort(np.asarray(g.values)) for g in t.column("grams")]
        top = {p: p for p in part}

        def root(p: str) -> str:
            while top[p] != p:
                p = top[p]
            return p

        a, b = [], []
        for r in (k for k, m in enumerate(mine) if m == i):
            for c in (k for k, m in enumerate(mine) if m == j):
                x, y = grams[r], grams[c]
                if root(part[r]) == root(part[c]) or 100 * min(len(x), len(y)) < percent * max(len(x), len(y)):
                    continue
                both = len(np.intersect1d(x, y, assume_unique=True))
                if 100 * both >= percent * (len(x) + len(y) - both):
                    top[root(part[c])] = root(part[r])
                    a.append(digest[r])
                    b.append(digest[c])
        return pa.table({"a": pa.array(a, pa.string()), "b": pa.array(b, pa.string())})

    return dealt.groupBy("bucket", "i", "j").applyInArrow(run, "a string, b string")


def components(docs: DataFrame, jaccard: float = 0.8, bands: int = 24) -> DataFrame:
    """(doc_id, component): the least id that links lead to; a document without words stands alone."""
    percent = round(100 * jaccard)
    keyed = docs.select("doc_id", F.md5(F.coalesce(canonical(F.col("text")), F.lit("")).cast("binary")).alias("digest"), "text")
    reps = keyed.groupBy("digest").agg(F.min("doc_id").alias("rep"), F.first("text").alias("text"))
    sets = stored(reps.select("digest", "rep", shingle_hashes(F.col("text")).alias("grams")))
    hits = _buckets(sets, bands)
    shared = stored(hits.groupBy("bucket").agg(F.count(F.lit(1)).alias("m"), F.min("digest").alias("head")).where("m > 1"))
    members = stored(hits.join(shared, "bucket").select("bucket", "digest", "head", "m"))
    links = stored(_confirmed(members.where("digest != head").select(F.col("digest").alias("a"), F.col("head").alias("b")).distinct(), sets, percent))
    classes = connected_components(links, "a", "b", contract=True)
    part = F.coalesce("component", "digest")
    placed = members.where("m > 2").join(classes.withColumnRenamed("node", "digest"), "digest", "left").select("bucket", "digest", part.alias("part"))
    mixed = placed.groupBy("bucket").agg(F.min("part").alias("p"), F.max("part").alias("q")).where("p != q").select("bucket")
    more = stored(_across(placed.join(mixed, "bucket", "left_semi"), sets, percent))
    if not more.isEmpty():
        classes = connected_components(links.union(more), "a", "b", contract=True)
    own = sets.select("digest", "rep", F.size("grams").alias("n")).join(classes.withColumnRenamed("node", "digest"), "digest", "left").select("digest", "rep", "n", part.alias("part"))
    least = own.groupBy("part").agg(F.min("rep").alias("component"))
    heads = own.where("n > 0").join(least, "part").select("digest", "component")
    return keyed.select("doc_id", "digest").join(heads, "digest", "left").select("doc_id", F.coalesce("component", "doc_id").alias("component"))
