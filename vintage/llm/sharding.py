"""Operator 9: sharding by fixed virtual slots.

A record is hashed into one of thousands of slots, for good. Bytes and rows are
added up per slot, which is a table of fixed size, and a versioned map assigns
every slot to a shard so that the shards' bytes are near equal. ``shard`` stores
the map as version 1, or goes by the latest version where one is stored;
``rebalance_stored`` moves as few slots as reach the balance and stores the next
version. Records never change their slot.

The slot comes from the id and the content together, so neither a null id nor
one text that a third of all rows share can fill a slot: equal texts are spread
over the shards on purpose, as bytes could not be near equal otherwise. Defined
cases: a null text has no bytes; a null id hashes like a value of its own; fully
repeated rows share a slot; an empty table gives an empty result.
"""

from __future__ import annotations

import heapq
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import settle, shared_dir

SLOTS, OVERHEAD = 8192, 16


def measured(docs: DataFrame, id_col: str = "doc_id", text: str = "text", slots: int = SLOTS) -> DataFrame:
    """(id, size, text_crc32, slot_id): one pass over the texts, which go no further."""
    t = F.coalesce(F.col(text), F.lit(""))
    crc = F.crc32(t.cast("binary"))
    slot = F.pmod(F.xxhash64(F.col(id_col), crc, F.length(t)), F.lit(slots)).cast("int")
    return docs.select(F.col(id_col), (F.octet_length(t) + OVERHEAD).cast("long").alias("size"), crc.cast("long").alias("text_crc32"), slot.alias("slot_id"))


def slot_sums(records: DataFrame) -> DataFrame:
    return records.groupBy("slot_id").agg(F.sum("size").alias("bytes"), F.count(F.lit(1)).alias("rows"))


def assign(sums: dict[int, int], shards: int, slots: int = SLOTS) -> dict[int, int]:
    """Every slot, largest first, to the lightest shard; empty ones too, as later rows may fall into them."""
    heap = [(0, 0, k) for k in range(shards)]
    out = {}
    for slot in sorted({*sums, *range(slots)}, key=lambda s: (-sums.get(s, 0), s)):
        load, held, k = heapq.heappop(heap)
        out[slot] = k
        heapq.heappush(heap, (load + sums.get(slot, 0), held + 1, k))
    return out


def rebalance(current: dict[int, int], sums: dict[int, int], shards: int, tolerance: float = 0.01) -> dict[int, int]:
    """The next map: slots leave overfull or removed shards only, until all are within ``tolerance``."""
    load = [0] * shards
    out = {s: k for s, k in current.items() if k < shards}
    for s, k in out.items():
        load[k] += sums.get(s, 0)
    homeless = sorted((s for s in sums if s not in out), key=lambda s: (-sums[s], s))
    top = (1 + tolerance) * sum(sums.values()) / shards
    for k in range(shards):
        own = sorted((s for s, x in out.items() if x == k), key=lambda s: (sums.get(s, 0), s))
        while load[k] > top and own:
            s = own.pop()
            if load[k] - sums.get(s, 0) < 2 * sum(sums.values()) / shards - top:
                continue  # it would leave too little behind
            load[k] -= sums.get(s, 0)
            del out[s]
            homeless.append(s)
    heap = [(n, k) for k, n in enumerate(load)]
    heapq.heapify(heap)
    for s in sorted(homeless, key=lambda s: (-sums.get(s, 0), s)):
        n, k = heapq.heappop(heap)
        out[s] = k
        heapq.heappush(heap, (n + sums.get(s, 0), k))
    return out


def store_map(spark: SparkSession, path: str, mapping: dict[int, int], version: int) -> None:
    """Writes one version of the slot-to-shard map; a version that is there already is never overwritten."""
    spark.createDataFrame(sorted(mapping.items()), "slot_id int, shard int").coalesce(1).write.mode("error").parquet(f"{path}/version={version}")


def stored_maps(spark: SparkSession, path: str) -> DataFrame | None:
    """(slot_id, shard, version) of all versions; None where none is stored."""
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if not folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(folder):
        return None
    return spark.read.schema("slot_id int, shard int, version int").parquet(path)


def latest_map(spark: SparkSession, path: str) -> tuple[int, dict[int, int]]:
    """The newest version and its map; (0, {}) where none is stored. A map has as many rows as there are slots."""
    maps = stored_maps(spark, path)
    newest = maps.agg(F.max("version")).first()[0] if maps is not None else None
    return (newest, {r.slot_id: r.shard for r in maps.where(F.col("version") == newest).collect()}) if newest else (0, {})


def rebalance_stored(spark: SparkSession, path: str, records: DataFrame, shards: int, tolerance: float = 0.01) -> tuple[int, int]:
    """Edits the stored map for the records (as ``measured``) as they are now, and stores it as the next version.

    Returns the new version and how many slots moved.
    """
    version, current = latest_map(spark, path)
    sums = {r["slot_id"]: r["bytes"] for r in slot_sums(records).collect()}
    after = rebalance(current, {s: sums.get(s, 0) for s in {*sums, *current}}, shards, tolerance)
    store_map(spark, path, after, version + 1)
    return version + 1, sum(after[s] != k for s, k in current.items())


def shard(docs: DataFrame, shards: int = 40, id_col: str = "doc_id", text: str = "text", slots: int = SLOTS, maps: str | None = None) -> DataFrame:
    """(id, size, text_crc32, slot_id, shard, place): place counts a shard's rows from 0 without gaps.

    ``maps``: folder of the versioned map, whose latest version decides; without one, a
    first version is made from these rows and stored there. By default that is a new folder of the shared one.
    The sums that reach the driver have at most ``slots`` rows. A place is the
    row's rank in its slot plus the rows of the shard's earlier slots.
    """
    spark = docs.sparkSession
    records = settle(measured(docs, id_col, text, slots))
    sums = {r["slot_id"]: (r["bytes"], r["rows"]) for r in slot_sums(records).collect()}
    maps = maps or f"{shared_dir(spark)}/slot-map-{uuid.uuid4().hex}"
    version, mapping = latest_map(spark, maps)
    if not version:
        mapping = assign({s: b for s, (b, _) in sums.items()}, shards, slots)
        store_map(spark, maps, mapping, 1)
    before, at = {}, [0] * (max(mapping.values(), default=0) + 1)
    for s in sorted(sums):
        before[s] = at[mapping[s]]
        at[mapping[s]] += sums[s][1]
    plan = spark.createDataFrame([(s, mapping[s], before[s]) for s in sorted(sums)], "slot_id int, shard int, ahead long")
    rank = F.row_number().over(Window.partitionBy("slot_id").orderBy(id_col, "text_crc32", "size")) - 1
    return records.withColumn("_rank", rank).join(F.broadcast(plan), "slot_id").select(id_col, "size", "text_crc32", "slot_id", "shard", (F.col("ahead") + F.col("_rank")).cast("long").alias("place"))
