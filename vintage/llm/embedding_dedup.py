"""Operator 1: embedding near-duplicates by int8 tile products with error bounds.

Every vector is normalised and quantised to int8 with its own scale; the norm of
what the rounding leaves is kept with it. For two vectors the quantised product
is then within ``e_i + (1 + e_i) * e_j`` of the cosine, by Cauchy-Schwarz, so a
pair whose product lies further below the threshold can't be a link, one further
above must be, and only pairs in between are recomputed in double precision.

Exact copies collapse before any product. Distinct vectors are laid into tiles
along their angles to pivots; two tiles whose angle intervals to some pivot lie
further apart than the threshold's angle hold no link (triangle inequality on
the sphere) and are never multiplied. A tile product returns, for each vector,
its number of links and one edge of a spanning forest, never the pairs.

Defined cases: null, zero-length, all-zero vectors, or ones with a null or
non-finite component, and rows without an id link with nothing; such a row is
its own component and is kept. Vectors of different lengths never link. Repeated
rows count as vectors of their own in ``n_links``. An empty table gives an empty
result. Columns of the input other than the two named ones are not used.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.components import connected_components
from .common import settle

SLACK = 1e-9


def usable(vector: str) -> Column:
    """True where a vector can link: not null, finite throughout, not all zero."""
    v = F.col(vector)
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return F.coalesce(fine & F.exists(v, lambda x: x != 0), F.lit(False))


def quantise(unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows of unit length as int8, their scales, and bounds on what is lost."""
    scale = np.abs(unit).max(axis=1) / 127
    q = np.rint(unit / scale[:, None]).astype(np.int8)
    lost = np.sqrt(((unit - q * scale[:, None]) ** 2).sum(axis=1)) + SLACK
    return q, scale, lost


def forest(links: np.ndarray, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Least id reachable inside one block of links, for its rows and its columns."""
    a, b = left.copy(), right.copy()
    top = np.iinfo(np.int64).max
    while True:
        a2 = np.minimum(a, np.where(links, b[None, :], top).min(axis=1))
        b2 = np.minimum(b, np.where(links, a2[:, None], top).min(axis=0))
        if (a2 == a).all() and (b2 == b).all():
            return a2, b2
        a, b = a2, b2


def tile_links(x: np.ndarray, y: np.ndarray, threshold: float, same: bool) -> tuple[np.ndarray, int]:
    """Boolean links of two tiles of raw vectors, and how many pairs were recomputed."""
    nx, ny = np.sqrt((x * x).sum(axis=1)), np.sqrt((y * y).sum(axis=1))
    (qx, sx, ex), (qy, sy, ey) = quantise(x / nx[:, None]), quantise(y / ny[:, None])
    exact_in = np.float32 if x.shape[1] * 127 * 127 < 1 << 24 else np.float64  # sums of int8 products stay whole
    about = (qx.astype(exact_in) @ qy.astype(exact_in).T).astype(np.float64)
    about *= sx[:, None]
    about *= sy[None, :]
    bound = ex[:, None] + (1 + ex)[:, None] * ey[None, :]
    links = about >= threshold + bound
    open_i, open_j = np.nonzero((about >= threshold - bound) & ~links)
    for k in range(0, len(open_i), 65_536):
        i, j = open_i[k : k + 65_536], open_j[k : k + 65_536]
        links[i, j] = np.einsum("ij,ij->i", x[i], y[j]) / (nx[i] * ny[j]) >= threshold
    if same:
        np.fill_diagonal(links, False)
    return links, len(open_i)


def near_duplicates(vectors: DataFrame, id_col: str = "vec_id", vector: str = "embedding", threshold: float = 0.9, tile_rows: int = 2048, pivots: int = 16, sample_rows: int = 4096) -> DataFrame:
    """(id, n_links, component_id, kept) for each row. ``sample_rows`` bounds the
    rows that pivots are chosen from; they steer pruning only, never the result."""
    rows = vectors.select(F.col(id_col).alias("id"), F.col(vector).alias("v"))
    good = rows.where(F.col("id").isNotNull() & usable("v"))
    size = F.size("v")
    reps = settle(good.groupBy("v").agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("copies")))
    tiles = _tiles(reps.withColumn("dim", size), tile_rows, pivots, sample_rows, threshold)
    found = settle(_products(tiles, threshold, pivots))
    comp = connected_components(found.select("rep", "edge"), "rep", "edge", contract=True)
    more = found.groupBy("rep").agg(F.sum("links").alias("links"))
    per_rep = (
        reps.join(more, "rep", "left").join(comp.withColumnRenamed("node", "rep"), "rep", "left")
        .select("v", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    )
    linked = good.join(per_rep, "v").select("id", "n_links", "component_id")
    alone = rows.where(~(F.col("id").isNotNull() & usable("v"))).select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    out = linked.union(alone)
    return out.select(F.col("id").alias(id_col), F.col("n_links").cast("long").alias("n_links"), "component_id", F.coalesce(F.col("id") == F.col("component_id"), F.lit(True)).alias("kept"))


def _tiles(reps: DataFrame, tile_rows: int, pivots: int, sample_rows: int, threshold: float) -> DataFrame:
    """One row a tile: ids, copies and raw vectors as bytes, and its angle interval to each pivot.

    Rows are range-partitioned by (length, nearest pivot, angle to it) and cut
    every ``tile_rows`` rows, so a tile is never larger, whatever the data.
    """
    sample = [r["v"] for r in reps.select("v").limit(sample_rows).collect()]
    dims = {len(x) for x in sample}
    main = max(dims, key=lambda d: sum(len(x) == d for x in sample), default=0)
    if sample:
        x = np.array([v for v in sample if len(v) == main], dtype=np.float64)
        x /= np.sqrt((x * x).sum(axis=1))[:, None]
        chosen, best = [0], x @ x[0]
        while len(chosen) < min(pivots, len(x)):  # the least like those chosen so far
            chosen.append(int(best.argmin()))
            best = np.maximum(best, x @ x[chosen[-1]])
        centres = x[chosen]
    else:
        centres = np.zeros((0, 0))
    is_float = dict(reps.dtypes)["v"] == "array<float>"
    raw = np.float32 if is_float else np.float64

    def angles(batches):
        for b in batches:
            v = b.column("v")
            dim = b.column("dim").to_numpy()
            near, far = np.zeros(len(dim), np.int32), np.zeros(len(dim))
            at = np.flatnonzero(dim == main) if len(centres) else np.empty(0, int)
            if len(at):
                m = np.array([v[int(i)].as_py() for i in at], dtype=np.float64)
                cos = (m / np.sqrt((m * m).sum(axis=1))[:, None]) @ centres.T
                near[at], far[at] = cos.argmax(axis=1), np.arccos(np.clip(cos.max(axis=1), -1, 1))
            yield pa.RecordBatch.from_arrays([b.column("rep"), b.column("copies"), v, b.column("dim"), pa.array(near), pa.array(far)], ["rep", "copies", "v", "dim", "near", "far"])

    kinds = dict(reps.dtypes)
    placed = reps.select("rep", "copies", "v", "dim").mapInArrow(angles, f"rep {kinds['rep']}, copies long, v {kinds['v']}, dim int, near int, far double")
    placed = settle(placed)
    ranged = placed.repartitionByRange("dim", "near", "far").sortWithinPartitions("dim", "near", "far")

    def cut(batches):
        held: list[tuple] = []

        def tile():
            ids, copies, vs = zip(*held, strict=True)
            m = np.array(vs, dtype=raw)
            u = m.astype(np.float64)
            u /= np.sqrt((u * u).sum(axis=1))[:, None]
            if len(centres) and m.shape[1] == main:
                t = np.arccos(np.clip(u @ centres.T, -1, 1))
                lo, hi = t.min(axis=0).tolist(), t.max(axis=0).tolist()
            else:
                lo = hi = [0.0] * len(centres)
            return {"first": ids[0], "n": len(ids), "dim": m.shape[1], "ids": np.array(ids, np.int64).tobytes(), "copies": np.array(copies, np.int64).tobytes(), "raw": m.tobytes(), "lo": lo, "hi": hi}

        schema = pa.schema([("first", pa.int64()), ("n", pa.int32()), ("dim", pa.int32()), ("ids", pa.binary()), ("copies", pa.binary()), ("raw", pa.binary()), ("lo", pa.list_(pa.float64())), ("hi", pa.list_(pa.float64()))])
        for b in batches:
            for row in zip(b.column("rep").to_pylist(), b.column("copies").to_pylist(), b.column("v").to_pylist(), strict=True):
                if held and (len(held) == tile_rows or len(held[0][2]) != len(row[2])):
                    yield pa.RecordBatch.from_pylist([tile()], schema)
                    held = []
                held.append(row)
        if held:
            yield pa.RecordBatch.from_pylist([tile()], schema)

    tiles = ranged.select("rep", "copies", "v").mapInArrow(cut, "first long, n int, dim int, ids binary, copies binary, raw binary, lo array<double>, hi array<double>")
    return settle(tiles.withColumn("single", F.lit(is_float)))


def _products(tiles: DataFrame, threshold: float, pivots: int, block: int = 512) -> DataFrame:
    """(rep, links, edge) from every pair of tiles that angles can't rule out.

    Which pairs those are is found on the tiles' summaries alone, dealt to tasks
    by pairs of summary blocks; the surviving pairs fetch their tiles by id.
    """
    reach = math.acos(threshold) + 1e-6
    blocks = max(1, -(-tiles.count() // block))
    head = tiles.select("first", "dim", "lo", "hi", F.pmod(F.xxhash64("first"), F.lit(blocks)).cast("int").alias("blk"))
    ids = F.sequence(F.lit(0), F.lit(blocks - 1))
    dealt = head.withColumn("other", F.explode(ids)).select("first", "dim", "lo", "hi", "blk", F.least("blk", "other").alias("bi"), F.greatest("blk", "other").alias("bj"))

    def pairs(t: pa.Table) -> pa.Table:
        bi, bj = t.column("bi")[0].as_py(), t.column("bj")[0].as_py()
        blk, first, dim = (t.column(c).to_numpy() for c in ("blk", "first", "dim"))
        lo, hi = (np.array(t.column(c).to_pylist(), dtype=np.float64).reshape(len(blk), -1) for c in ("lo", "hi"))
        left, right = np.flatnonzero(blk == bi), np.flatnonzero(blk == bj)
        a, b = [], []
        for i in left:
            apart = np.maximum(lo[right] - hi[i], lo[i] - hi[right]).max(axis=1, initial=-1.0)
            j = right[(apart <= reach) & (dim[right] == dim[i]) & ((first[right] >= first[i]) | (bi != bj))]
            a.append(np.full(len(j), first[i]))
            b.append(first[j])
        return pa.table({"i": np.concatenate(a) if a else np.empty(0, np.int64), "j": np.concatenate(b) if b else np.empty(0, np.int64)})

    wanted = dealt.groupBy("bi", "bj").applyInArrow(pairs, "i long, j long")
    body = tiles.select("first", "dim", "ids", "copies", "raw", "single")
    left = body.select(F.col("first").alias("i"), *(F.col(c).alias(f"l_{c}") for c in ("dim", "single", "ids", "copies", "raw")))
    right = body.select(F.col("first").alias("j"), *(F.col(c).alias(f"r_{c}") for c in ("ids", "copies", "raw")))
    # The pair table is spread first: which tiles meet, not which tile is popular, decides where a product runs.
    met = wanted.join(left, "i").join(right, "j")

    def multiply(batches):
        for b in batches:
            for k in range(b.num_rows):
                r = {n: b.column(n)[k].as_py() for n in b.schema.names}
                kind = np.float32 if r["l_single"] else np.float64
                x, y = (np.frombuffer(r[c], kind).reshape(-1, r["l_dim"]).astype(np.float64) for c in ("l_raw", "r_raw"))
                li, ri, lc, rc = (np.frombuffer(r[c], np.int64) for c in ("l_ids", "r_ids", "l_copies", "r_copies"))
                same = r["i"] == r["j"]
                links, _ = tile_links(x, y, threshold, same)
                at, to = np.flatnonzero(links.any(axis=1)), np.flatnonzero(links.any(axis=0))
                if not len(at):
                    continue
                part = links[np.ix_(at, to)]
                ea, eb = forest(part, li[at], ri[to])
                out = [(li[at], part @ rc[to], ea)]
                if not same:
                    out.append((ri[to], part.T @ lc[at], eb))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(z)) for z in zip(*out, strict=True)], ["rep", "links", "edge"])

    return met.mapInArrow(multiply, "rep long, links long, edge long")
