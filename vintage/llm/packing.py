"""Operator 6: packing by dominance reduction, then best fit.

Documents become token pieces of at most the capacity; only longer ones are cut.
What a packing needs of them is how many pieces there are of each length, a
table of at most ``capacity`` rows however large the corpus, and that is all the
driver sees. On it, sets that provably dominate every alternative are fixed for
good (a piece nothing fits beside; a pair that fills a sequence; a pair where no
second companion fits; a pair no set of two companions exceeds; a triple no
other pair of companions exceeds, item by item), which shrinks the instance; the
rest goes by best fit, longest first. Equal lengths are handled at once, so the
plan is a list of ranges: ranks r..r+n of a length go to n sequences in a row at
one offset. Pieces get their rank within their length from counts per salted
sub-group, never from one group of all, and look their range up.

Defined cases: a null or empty text is the end mark alone; repeated rows and
null ids are pieces of their own; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import encoding, is_plain, vocabulary_path
from .common import settle, slices, texts_of

CAPACITY, END_ID = 2048, 0
#: One vocabulary in the forms that two libraries read.
VOCABULARY, RANKS = "byte_bpe_50k.json", "byte_bpe_50k.tiktoken"


class Ids:
    """Token ids as the tokenizers library gives them.

    Texts of plain characters go through the rank file of the same vocabulary,
    which gives the same ids several times faster; all others, on whose classes
    Unicode versions could differ, go through the tokenizers library itself.
    """

    def __init__(self, vocabulary: str = VOCABULARY, ranks: str = RANKS):
        from tokenizers import Tokenizer

        self.fast = encoding(vocabulary_path(ranks))
        self.exact = Tokenizer.from_file(vocabulary_path(vocabulary))
        self.exact.encode_special_tokens = True

    def __call__(self, text: str) -> np.ndarray:
        if is_plain(text):
            return self.fast.encode_to_numpy(text, disallowed_special=())
        return np.array(self.exact.encode(text, add_special_tokens=False).ids, np.uint32)


def cuts(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces; the first takes what is left over."""
    if n <= capacity:
        return [(0, n)]
    first = n % capacity or capacity
    return [(0, first), *((s, capacity) for s in range(first, n, capacity))]


def pieces(docs: DataFrame, id_col: str = "doc_id", text: str = "text", capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """(id, piece, start, length, ids_crc32[, ids]) for each piece of each row."""
    kind = dict(docs.dtypes)[id_col]
    lean = docs.select(F.col(id_col).alias("id"), F.col(text).alias("text"))

    def run(batches):
        encode = Ids()
        for b in slices(batches, "text"):
            row, piece, start, length, crc, ids = [], [], [], [], [], []
            for k, t in enumerate(texts_of(b, "text")):
                own = np.append(encode(t), np.uint32(END_ID)).astype("<u4")
                for p, (s, n) in enumerate(cuts(len(own), capacity)):
                    part = own[s : s + n]
                    row.append(k), piece.append(p), start.append(s), length.append(n), crc.append(zlib.crc32(part.tobytes()))
                    if with_ids:
                        ids.append(part.astype(np.int32))
            cols = [b.column("id").take(pa.array(row, pa.int32())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())]
            names = ["id", "piece", "start", "length", "ids_crc32"]
            yield pa.RecordBatch.from_arrays([*cols, *([pa.array(ids, pa.list_(pa.int32()))] if with_ids else [])], [*names, *(["ids"] if with_ids else [])])

    out = lean.mapInArrow(run, f"id {kind}, piece int, start long, length long, ids_crc32 long" + (", ids array<int>" if with_ids else ""))
    return out.withColumnRenamed("id", id_col)


class Plan:
    """Ranges (length, first rank, how many, first sequence, offset) of a packing."""

    def __init__(self, counts: dict[int, int], capacity: int = CAPACITY):
        self.capacity, self.ranges, self.sequences = capacity, [], 0
        self.left = [0] * (capacity + 1)
        for k, n in counts.items():
            self.left[k] = n
        self.taken = [0] * (capacity + 1)
        self.present = sum(1 << k for k, n in counts.items() if n)
        self.fixed = 0

    def bound(self) -> int:
        """No packing needs fewer sequences than its tokens fill."""
        return -(-sum(k * n for k, n in enumerate(self.left)) // self.capacity)

    def _take(self, k: int, n: int, sequence: int, offset: int) -> None:
        self.ranges.append((k, self.taken[k], n, sequence, offset))
        self.taken[k] += n
        self.left[k] -= n
        if not self.left[k]:
            self.present &= ~(1 << k)

    def _fix(self, lengths: tuple[int, ...], times: int) -> None:
        offset = 0
        for k in lengths:
            self._take(k, times, self.sequences, offset)
            offset += k
        self.sequences += times
        self.fixed += times

    def _largest(self, limit: int, without: tuple[int, ...] = ()) -> int:
        """The longest present length up to ``limit``, counting out one piece for each of ``without``; 0 if none."""
        mask = self.present & ((2 << max(limit, 0)) - 1)
        while mask:
            k = mask.bit_length() - 1
            if self.left[k] > without.count(k):
                return k
            mask &= ~(1 << k)
        return 0

    def _least(self, how_many: int, without: int) -> int:
        """Sum of the ``how_many`` shortest pieces beside one of ``without``; beyond the capacity if there are fewer."""
        mask, total = self.present, 0
        while mask:
            k = (mask & -mask).bit_length() - 1
            n = min(how_many, self.left[k] - (k == without))
            total, how_many = total + n * k, how_many - n
            if not how_many:
                return total
            mask &= mask - 1
        return self.capacity + 1

    def reduce(self) -> None:
        """Fix dominating sets around each length, longest first, until nothing more is certain."""
        changed = True
        while changed:
            changed = False
            for j in range(self.capacity, 0, -1):
                while self.left[j] and (found := self._dominating(j)):
                    self._fix(*found)
                    changed = True

    def _dominating(self, j: int) -> tuple[tuple[int, ...], int] | None:
        room = self.capacity - j
        k = self._largest(room, (j,))
        if not k:
            # Alone; if only its own kind could join it, one of them is still alone.
            return (j,), self.left[j] if j > room else 1
        times = self.left[j] // 2 if j == k else min(self.left[j], self.left[k])
        if k == room or self._least(2, j) > room:
            return (j, k), times
        if self._least(3, j) > room:  # at most two companions, so all sets are known
            if self._best_pair(room, j) <= k:
                return (j, k), 1
            b = self._largest(room - k, (j, k))
            if b:
                larger = self._next_above(b, j)
                # No pair of companions with a smaller member above b: then (k, b) is at least any pair, member by member.
                if not larger or 2 * larger > room:
                    return (j, k, b), 1
        return None

    def _best_pair(self, room: int, j: int) -> int:
        best, mask = 0, self.present & ((2 << room) - 1)
        while mask:
            a = mask.bit_length() - 1
            mask &= ~(1 << a)
            if 2 * a <= best:
                break
            if self.left[a] > (a == j) and (b := self._largest(min(a, room - a), (j, a))):
                best = max(best, a + b)
        return best

    def _next_above(self, b: int, j: int) -> int:
        mask = self.present >> (b + 1) << (b + 1)
        while mask:
            k = (mask & -mask).bit_length() - 1
            if self.left[k] > (k == j):
                return k
            mask &= mask - 1
        return 0

    def best_fit(self) -> None:
        """The rest, longest first, each to the fullest sequence that has room."""
        room: list[list[tuple[int, int]]] = [[] for _ in range(self.capacity + 1)]  # by free tokens: runs of sequences
        mask = 0
        for k in range(self.capacity, 0, -1):
            while self.left[k]:
                fits = mask >> k
                if fits:
                    free = k + (fits & -fits).bit_length() - 1
                    first, n = room[free].pop()
                    if not room[free]:
                        mask &= ~(1 << free)
                else:
                    free, first, n = self.capacity, self.sequences, -(-self.left[k] // (self.capacity // k))
                    self.sequences += n
                # One sequence takes equal pieces until it has no room for another.
                each = free // k
                full = min(n, self.left[k] // each)
                if not full:
                    each, full = self.left[k], 1
                for i in range(each):
                    self._take(k, full, first, self.capacity - free + i * k)
                for rest, at, count in ((free - each * k, first, full), (free, first + full, n - full)):
                    if count and rest:
                        room[rest].append((at, count))
                        mask |= 1 << rest

    def solve(self) -> Plan:
        self.reduce()
        self.best_fit()
        return self

    def arrays(self) -> tuple[np.ndarray, np.ndarray]:
        """Ranges sorted for look-up, and their keys (length and first rank as one number)."""
        r = np.array(sorted(self.ranges), np.int64).reshape(-1, 5)
        return r, r[:, 0] << 48 | r[:, 1]


def pack(rows: DataFrame, length: str = "length", capacity: int = CAPACITY, order: tuple[str, ...] = ("doc_id", "piece")) -> DataFrame:
    """The rows with sequence_id and offset. Lengths are 1 to ``capacity``."""
    spark = rows.sparkSession
    rows = settle(rows)
    counts = {int(r[0]): int(r[1]) for r in rows.groupBy(length).agg(F.count(F.lit(1))).collect()}
    plan = Plan(counts, capacity).solve()
    salts = max(64, sum(counts.values()) // 100_000)
    salted = rows.withColumn("_salt", F.pmod(F.xxhash64(*order), F.lit(salts)))
    groups = salted.groupBy(length, "_salt").agg(F.count(F.lit(1)).alias("_n"))
    ahead = groups.withColumn("_ahead", F.sum("_n").over(Window.partitionBy(length).orderBy("_salt")) - F.col("_n")).select(length, "_salt", "_ahead")
    inner = F.row_number().over(Window.partitionBy(length, "_salt").orderBy(*order)) - 1
    ranked = salted.withColumn("_rank", inner).join(ahead, [length, "_salt"]).withColumn("_rank", F.col("_rank") + F.col("_ahead")).drop("_salt", "_ahead")
    shipped = spark.sparkContext.broadcast(plan.arrays())

    def place(batches):
        r, keys = shipped.value
        for b in batches:
            n, rank = b.column(length).to_numpy(), b.column("_rank").to_numpy()
            at = np.searchsorted(keys, n.astype(np.int64) << 48 | rank, side="right") - 1
            sequence, offset = r[at, 3] + rank - r[at, 1], r[at, 4]
            names = [x for x in b.schema.names if x != "_rank"]
            yield pa.RecordBatch.from_arrays([*(b.column(x) for x in names), pa.array(sequence), pa.array(offset)], [*names, "sequence_id", "offset"])

    fields = [f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields]
    return ranked.select(*rows.columns, "_rank").mapInArrow(place, ", ".join([*fields, "sequence_id long, offset long"]))
