"""Operator 8: near-duplicate documents by b-bit MinHash.

A document is its set of five-word shingles. 96 minima give 24 bands of four;
two documents that share a band are candidates, which two sets at the least
similarity of 0.85 fail to do with a chance of 2e-8. The low four bits of each
minimum, packed into 48 bytes, estimate a candidate pair's similarity with the
chance agreement of 1/16 taken out; pairs that the estimate puts far below the
threshold go, all others are confirmed on their full sets.

Equal texts collapse before any of it. Members of a bucket are first compared
with one of them, the one that shares most bands overall (in a family of copies
that is their origin). Only buckets that this leaves in several components are
looked at pair by pair, in blocks, and only pairs across components; so groups
of copies of any size cost about one comparison a member, and no link between
components is lost.

Defined cases: a null text, or one without words, has an empty set and links
with nothing; fewer than five words are one shingle; rows without an id get
null as their component and are kept; repeated rows come back once each; an
empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import connected_components
from .common import settle, slices, texts_of
from .words import MIX_1, mix, shingle_sets

BANDS, ROWS, BITS = 24, 4, 4
BLOCK_WORDS = 1 << 19
PERMS = BANDS * ROWS
#: Odd multipliers and offsets of the 96 permutations of 32-bit values, from a fixed seed.
_RNG = np.random.default_rng(20240501)
_MULT = _RNG.integers(0, 1 << 32, PERMS, dtype=np.uint32) | np.uint32(1)
_PLUS = _RNG.integers(0, 1 << 32, PERMS, dtype=np.uint32)
_BAND = mix(np.arange(1, ROWS + 1, dtype=np.uint64) * np.uint64(MIX_1)) | np.uint64(1)


def minima(sets: list[np.ndarray]) -> np.ndarray:
    """Least value under each permutation, for non-empty sets (one row each)."""
    x = np.concatenate(sets)
    x = (x ^ (x >> np.uint64(32))).astype(np.uint32)
    at = np.concatenate([[0], np.cumsum([len(s) for s in sets])[:-1]])
    out = np.empty((len(sets), PERMS), np.uint32)
    work = np.empty_like(x)
    for k in range(PERMS):
        np.multiply(x, _MULT[k], out=work)
        np.add(work, _PLUS[k], out=work)
        np.bitwise_xor(work, work >> np.uint32(15), out=work)  # else low bits follow from low bits alone
        np.minimum.reduceat(work, at, out=out[:, k])
    return out


def band_keys(m: np.ndarray) -> np.ndarray:
    """One 64-bit key a band; the band's number is part of the key."""
    parts = m.reshape(len(m), BANDS, ROWS).astype(np.uint64)
    key = (parts * _BAND).sum(axis=2, dtype=np.uint64) + np.arange(1, BANDS + 1, dtype=np.uint64) * np.uint64(MIX_1)
    return mix(key).view(np.int64)


def packed(m: np.ndarray) -> np.ndarray:
    """The low four bits of every minimum, two to a byte."""
    low = (m & np.uint32(15)).astype(np.uint8)
    return low[:, ::2] << 4 | low[:, 1::2]


def estimate(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Similarity from packed signatures (rows of ``a`` against rows of ``b``), chance agreement removed."""
    d = a ^ b
    agree = ((d & 0xF0) == 0).sum(axis=-1) + ((d & 0x0F) == 0).sum(axis=-1)
    chance = 1 / (1 << BITS)
    return (agree / PERMS - chance) / (1 - chance)


def floor_of(threshold: float, sigmas: float = 6.0) -> float:
    """An estimate below this is no link: six standard deviations under the threshold."""
    return threshold - sigmas * float(np.sqrt(threshold * (1 - threshold) / PERMS)) - 0.02


def is_link(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """100 * intersection >= percent * union, on sorted distinct hashes."""
    small, large = (len(a), len(b)) if len(a) < len(b) else (len(b), len(a))
    if 100 * small < percent * large:
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def signatures(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, digest of the text, n_shingles, bands, sig) for each row; bands and sig are null for empty sets."""
    kind = dict(docs.dtypes)[id_col]
    lean = docs.select(F.col(id_col).alias("id"), F.md5(F.col(text).cast("binary")).alias("digest"), F.col(text).alias("text"))

    def run(batches):
        for b in slices(batches, "text"):
            sets = shingle_sets([t.encode("utf-8", "surrogatepass") for t in texts_of(b, "text")])
            sizes = np.array([len(s) for s in sets], np.int64)
            full = np.flatnonzero(sizes)
            bands: list = [None] * len(sets)
            sigs: list = [None] * len(sets)
            if len(full):
                m = minima([sets[k] for k in full])
                keys, sig = band_keys(m), packed(m)
                for row, k in enumerate(full):
                    bands[k], sigs[k] = keys[row], sig[row].tobytes()
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("digest"), pa.array(sizes), pa.array(bands, pa.list_(pa.int64())), pa.array(sigs, pa.binary())], ["id", "digest", "n_shingles", "bands", "sig"])

    return lean.mapInArrow(run, f"id {kind}, digest string, n_shingles long, bands array<long>, sig binary")


def texts_by_digest(docs: DataFrame, wanted: DataFrame, id_col: str, text: str) -> DataFrame:
    """(digest, text) of the documents whose ids are ``wanted``: one id stands for all copies of a text, so copies never meet in a task."""
    # The ids grow with the documents, so they are never broadcast, however few they look.
    known = docs.select(F.col(id_col).alias("id"), F.col(text).alias("text")).join(wanted.hint("merge"), "id", "left_semi")
    return settle(known.groupBy(F.md5(F.col("text").cast("binary")).alias("digest")).agg(F.first("text").alias("text")))


def confirm(pairs: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) of text digests whose full shingle sets are similar enough."""
    first = pairs.join(texts.select(F.col("digest").alias("a"), F.col("text").alias("ta")), "a")
    both = first.join(texts.select(F.col("digest").alias("b"), F.col("text").alias("tb")), "b").select("a", "b", "ta", "tb")

    def run(batches):
        last, kept = None, None
        for whole in batches:
            for b in slices(iter([whole]), "ta"):
                a, c = b.column("a").to_pylist(), b.column("b").to_pylist()
                ta, tb = b.column("ta").to_pylist(), b.column("tb").to_pylist()
                fine = []
                for k in range(len(a)):
                    if c[k] != last:  # rows mostly come sorted by b
                        last, kept = c[k], shingle_sets([tb[k].encode("utf-8", "surrogatepass")])[0]
                    fine.append(is_link(shingle_sets([ta[k].encode("utf-8", "surrogatepass")])[0], kept, percent))
                yield pa.RecordBatch.from_arrays([b.column("a"), b.column("b")], ["a", "b"]).filter(pa.array(fine, pa.bool_()))

    return both.mapInArrow(run, "a string, b string")


def common(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections of two lists of distinct hashes, as one matrix product."""
    values, at = np.unique(np.concatenate([*left, *right]), return_inverse=True)
    row = np.repeat(np.arange(len(left) + len(right)), [len(x) for x in (*left, *right)])
    several = np.bincount(at, minlength=len(values)) > 1  # a hash of one set is in no intersection
    column = np.cumsum(several) - 1
    keep = several[at]
    row, at = row[keep], column[at[keep]]
    out = np.zeros((len(left), len(right)), np.float32)
    for start in range(0, int(several.sum()), 8192):
        part = (at >= start) & (at < start + 8192)
        m = np.zeros((len(left) + len(right), 8192), np.float32)
        m[row[part], at[part] - start] = 1
        out += m[: len(left)] @ m[len(left) :].T
    return out.astype(np.int64)


def forest(links: np.ndarray, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Least number reachable inside one block of links, for its rows and its columns."""
    a, b, top = left, right, np.iinfo(np.int64).max
    while True:
        a2 = np.minimum(a, np.where(links, b[None, :], top).min(axis=1, initial=top))
        b2 = np.minimum(b, np.where(links, a2[:, None], top).min(axis=0, initial=top))
        if (a2 == a).all() and (b2 == b).all():
            return a2, b2
        a, b = a2, b2


def _across(left: DataFrame, texts: DataFrame, percent: int, block: int) -> DataFrame:
    """Links (a, b) between members of one bucket that are in different components.

    ``left``: (bucket, digest, sig, part, size), one row a member of a bucket that
    still holds several components. Each pair of blocks of members is one group:
    estimates pick who may link, full sets decide, and what leaves the group is
    a spanning forest of its links, at most a row for each member.
    """
    # A block holds at most about ``block`` members and BLOCK_WORDS words, so long texts make small blocks.
    sizes = left.groupBy("bucket").agg(F.count(F.lit(1)).alias("m"), F.sum("size").alias("words"))
    blocks = F.greatest(F.ceil(F.col("m") / block), F.ceil(F.col("words") / BLOCK_WORDS)).cast("int")
    dealt = left.join(sizes, "bucket").withColumn("blocks", blocks).withColumn("mine", F.pmod(F.xxhash64("digest"), "blocks").cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("bucket", "digest", "sig", "part", "mine", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"))
    low = floor_of(percent / 100)

    def run(t: pa.Table) -> pa.Table:
        i, j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
        mine, digest, text = t.column("mine").to_numpy(), t.column("digest").to_pylist(), t.column("text")
        _, part = np.unique(t.column("part").to_pylist(), return_inverse=True)
        sig = np.frombuffer(b"".join(t.column("sig").to_pylist()), np.uint8).reshape(len(mine), -1)
        rows, cols = np.flatnonzero(mine == i), np.flatnonzero(mine == j)
        may = np.zeros((len(rows), len(cols)), bool)
        for k, r in enumerate(rows):
            may[k] = (part[cols] != part[r]) & (estimate(sig[r], sig[cols]) >= low)
        rows, cols, may = rows[may.any(axis=1)], cols[may.any(axis=0)], may[np.ix_(may.any(axis=1), may.any(axis=0))]
        a, b = [], []
        if len(rows):
            sets = dict(zip(need := sorted({*rows.tolist(), *cols.tolist()}), shingle_sets([text[k].as_py().encode("utf-8", "surrogatepass") for k in need]), strict=True))
            x, y = [sets[k] for k in rows], [sets[k] for k in cols]
            both = common(x, y)
            size = np.array([len(s) for s in x])[:, None] + np.array([len(s) for s in y])[None, :] - both
            ra, cb = forest(may & (100 * both >= percent * size), rows, cols)
            for at, to in (*zip(rows.tolist(), ra.tolist(), strict=True), *zip(cols.tolist(), cb.tolist(), strict=True)):
                if at != to:
                    a.append(digest[at])
                    b.append(digest[to])
        return pa.table({"a": pa.array(a, pa.string()), "b": pa.array(b, pa.string())})

    return dealt.join(texts, "digest").groupBy("bucket", "i", "j").applyInArrow(run, "a string, b string")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text: str = "text", percent: int = 85, block: int = 512) -> DataFrame:
    """(id, n_shingles, component_id, kept) for each row; links need 100 * intersection >= percent * union."""
    rows = settle(signatures(docs, id_col, text))
    full = rows.where(F.col("sig").isNotNull() & F.col("id").isNotNull())
    reps = full.groupBy("digest").agg(F.min("id").alias("rep"), F.first("bands").alias("bands"), F.first("sig").alias("sig"), F.first("n_shingles").alias("size"))
    hits = reps.select("digest", "rep", "sig", "size", F.explode("bands").alias("bucket"))
    shared = hits.groupBy("bucket").agg(F.count(F.lit(1)).alias("m")).where("m > 1")
    members = settle(hits.join(shared, "bucket"))
    degree = members.groupBy("digest").agg(F.sum("m").alias("degree"))
    ranked = members.join(degree, "digest")
    hubs = ranked.groupBy("bucket").agg(F.max(F.struct("degree", "digest", "sig")).alias("hub")).select("bucket", F.col("hub.digest").alias("hub"), F.col("hub.sig").alias("hub_sig"))
    tried = members.join(hubs, "bucket").where("digest != hub").select("digest", "hub", "sig", "hub_sig").dropDuplicates(["digest", "hub"])
    close = _estimated(tried, floor_of(percent / 100))
    texts = texts_by_digest(docs, members.select(F.col("rep").alias("id")).distinct(), id_col, text)
    links = settle(confirm(close, texts, percent))
    comp = connected_components(links, "a", "b", contract=True)
    part = F.coalesce("component", "digest")
    placed = members.join(comp.withColumnRenamed("node", "digest"), "digest", "left").select("bucket", "digest", "sig", "size", part.alias("part"))
    several = placed.groupBy("bucket").agg(F.min("part").alias("p"), F.max("part").alias("q"), F.count(F.lit(1)).alias("m"))
    # A bucket of two has been compared in full already.
    mixed = placed.join(several.where("p != q and m > 2").select("bucket"), "bucket", "left_semi")
    more = settle(_across(mixed, texts, percent, block))
    if not more.isEmpty():
        links = links.union(more)
        comp = connected_components(links, "a", "b", contract=True)
    least = reps.join(comp.withColumnRenamed("node", "digest"), "digest", "left").select("digest", "rep", part.alias("part"))
    heads = least.groupBy("part").agg(F.min("rep").alias("component_id"))
    classes = least.join(heads, "part").select("digest", "component_id")
    out = rows.select("id", "digest", "n_shingles").join(classes, "digest", "left")
    own = F.when(F.col("n_shingles") > 0, F.coalesce("component_id", "id")).otherwise(F.col("id"))
    out = out.select("id", "n_shingles", F.when(F.col("id").isNotNull(), own).alias("component_id"))
    return out.select(F.col("id").alias(id_col), "n_shingles", "component_id", F.coalesce(F.col("id") == F.col("component_id"), F.lit(True)).alias("kept"))


def _estimated(pairs: DataFrame, low: float) -> DataFrame:
    """Pairs (a, b) whose b-bit estimate is at least ``low``."""

    def run(batches):
        for b in batches:
            x, y = (np.frombuffer(b"".join(b.column(c).to_pylist()), np.uint8).reshape(b.num_rows, -1) for c in ("sig", "hub_sig"))
            fine = pa.array(estimate(x, y) >= low)
            yield pa.RecordBatch.from_arrays([b.column("digest"), b.column("hub")], ["a", "b"]).filter(fine)

    return pairs.mapInArrow(run, "a string, b string")
