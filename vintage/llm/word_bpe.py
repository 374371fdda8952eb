"""Operator 3: byte-level BPE over a global shuffle of distinct words.

Whole texts are cut into pre-tokens. A chunk of documents lists its distinct
words once and, by position, which word stands where. Words are dealt to tasks
by their hash, each task encodes each distinct word once, and the ids travel to
the chunks' positions, which put them in order. A
chunk hands over its words packed by hash bucket, so the shuffle holds a row for
each chunk and bucket, not for each pre-token, and a word that every document
uses costs no more than a rare one. Decoding looks ids up in the token-byte
table, whose size is the vocabulary's, and so is broadcast.

Defined cases: a null text is empty and has no ids; very long texts form a chunk
of their own; repeated rows and ids come back as often as they stand; an id
outside the vocabulary decodes to nothing; an empty table gives an empty result.
Texts with lone surrogates can't occur in Spark's strings.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import WordCache, encoding, ragged, split, token_bytes, vocabulary_path
from .common import settle, slices, texts_of

CHUNK, PIECE = 6 << 20, 1 << 15
VOCABULARY = "byte_bpe_multi_50k.tiktoken"


def _pack(a: np.ndarray) -> bytes:
    return zlib.compress(a.tobytes(), 1)


def _unpack(b: bytes, kind) -> np.ndarray:
    return np.frombuffer(zlib.decompress(b), kind)


def _narrow(a: np.ndarray) -> tuple[bytes, bytes]:
    """Low and high halves apart: codes and ids then compress far better."""
    a = a.astype(np.uint32)
    return _pack((a & 0xFFFF).astype(np.uint16)), _pack((a >> 16).astype(np.uint16))


def _wide(low: bytes, high: bytes) -> np.ndarray:
    return _unpack(low, np.uint16).astype(np.int64) | _unpack(high, np.uint16).astype(np.int64) << 16


def _runs(counts: list[int], limit: int):
    """Ranges of documents of about ``limit`` pre-tokens each, at least one document."""
    start = total = 0
    for k, n in enumerate(counts):
        if k > start and total + n > limit:
            yield start, k
            start, total = k, 0
        total += n
    if start < len(counts):
        yield start, len(counts)


def _in_order(words, n_buckets: int) -> tuple[list[bytes], np.ndarray, np.ndarray]:
    """The distinct words of a chunk by bucket and then by bytes, where each bucket
    starts, and the place of each word in that order: the same whoever works it out."""
    raw = [w.encode("utf-8") for w in words]
    bucket = np.fromiter((zlib.crc32(w) % n_buckets for w in raw), np.int64, len(raw))
    order = sorted(range(len(raw)), key=raw.__getitem__)
    order = np.array(order, np.int64)[np.argsort(bucket[order], kind="stable")] if raw else np.empty(0, np.int64)
    place = np.empty(len(raw), np.int64)
    place[order] = np.arange(len(raw))
    return [raw[i] for i in order], np.searchsorted(bucket[order], np.arange(n_buckets + 1)), place


def _chunks(batches):
    """(chunk, sub-batch): a chunk's name is a digest of its rows' place and size, so both passes must cut alike."""
    part, seq = TaskContext.get().partitionId(), 0
    for b in slices(batches, "text", CHUNK):
        sizes = b.column("text").cast(pa.binary()).to_pylist()
        yield f"{part}/{seq}/{zlib.crc32(repr([x and len(x) for x in sizes]).encode()):08x}/{zlib.crc32(b''.join(x or b'' for x in sizes)):08x}", b
        seq += 1


def encode(docs: DataFrame, id_col: str = "doc_id", text: str = "text", vocabulary: str = VOCABULARY, buckets: int | None = None, plain_scan: bool = False) -> DataFrame:
    """(id, ids array<int>) for each row.

    Texts are cut twice: once for the words, which are dealt out by bucket, and
    once for the positions, which go to their chunk directly; that is cheaper
    than moving every position through the word tasks. Both passes must see the
    same chunks, so the input is written out first unless it is a ``plain_scan``
    of files; chunks that differ all the same end the job with an error.
    ``buckets`` word buckets, by default as many as the session's shuffle
    partitions, so they grow with the cluster's setting.
    """
    spark = docs.sparkSession
    n_buckets = buckets or max(16, int(spark.conf.get("spark.sql.shuffle.partitions")))
    kind = dict(docs.dtypes)[id_col]
    lean = docs.select(F.col(id_col).alias("id"), F.col(text).alias("text"))
    lean = lean if plain_scan else settle(lean)

    def list_words(batches):
        for chunk, b in _chunks(batches):
            seen: dict[str, None] = {}
            for t in texts_of(b, "text"):
                seen.update(dict.fromkeys(split(t)))
            words, cut, _ = _in_order(seen, n_buckets)
            rows = [(k, i, j) for k, (i, j) in enumerate(zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True)) if j > i]
            yield pa.RecordBatch.from_arrays([
                pa.array([chunk] * len(rows), pa.string()), pa.array([k for k, _, _ in rows], pa.int32()), pa.array([i for _, i, _ in rows], pa.int32()),
                pa.array([zlib.compress(b"".join(words[i:j]), 1) for _, i, j in rows], pa.binary()),
                pa.array([_pack(np.array([len(w) for w in words[i:j]], np.int32)) for _, i, j in rows], pa.binary()),
            ], ["chunk", "bucket", "first", "words", "lens"])

    def list_places(batches):
        for chunk, b in _chunks(batches):
            code: dict[str, int] = {}
            column, counts = [], []
            for t in texts_of(b, "text"):
                words = split(t)
                counts.append(len(words))
                column.append(np.fromiter((code.setdefault(w, len(code)) for w in words), np.int32, len(words)))
            _, _, place = _in_order(code, n_buckets)
            ids, rows = b.column("id"), list(_runs(counts, PIECE))
            halves = [_narrow(place[np.concatenate(column[i:j])] if sum(counts[i:j]) else np.empty(0, np.int64)) for i, j in rows]
            yield pa.RecordBatch.from_arrays([
                pa.array([chunk] * len(rows), pa.string()), pa.array([-1 - k for k in range(len(rows))], pa.int32()), pa.array([len(code)] * len(rows), pa.int32()),
                pa.array([x for x, _ in halves], pa.binary()), pa.array([x for _, x in halves], pa.binary()),
                pa.array([_pack(np.array(counts[i:j], np.int64)) for i, j in rows], pa.binary()),
                pa.ListArray.from_arrays(pa.array([0, *(j for _, j in rows)], pa.int32()), ids),
            ], ["chunk", "bucket", "first", "low", "high", "lens", "doc_ids"])

    words = lean.mapInArrow(list_words, "chunk string, bucket int, first int, words binary, lens binary").repartition("bucket")
    places = lean.mapInArrow(list_places, f"chunk string, bucket int, first int, low binary, high binary, lens binary, doc_ids array<{kind}>")

    def encode_words(batches):
        ranks = encoding(vocabulary_path(vocabulary))
        seen = WordCache(lambda w: np.array(ranks.encode_ordinary(w.decode("utf-8")), np.uint32).tobytes(), 200_000)
        for b in batches:
            lens, lows, highs = [], [], []
            for packed, sizes in zip(b.column("words").to_pylist(), b.column("lens").to_pylist(), strict=True):
                body, at, got = zlib.decompress(packed), 0, []
                for n in _unpack(sizes, np.int32).tolist():
                    got.append(seen[body[at : at + n]])
                    at += n
                low, high = _narrow(np.frombuffer(b"".join(got), np.uint32))
                lens.append(_pack(np.array([len(g) // 4 for g in got], np.int32))), lows.append(low), highs.append(high)
            yield pa.RecordBatch.from_arrays([b.column("chunk"), b.column("bucket"), b.column("first"), pa.array(lows, pa.binary()), pa.array(highs, pa.binary()), pa.array(lens, pa.binary())], ["chunk", "bucket", "first", "low", "high", "lens"])

    encoded = words.mapInArrow(encode_words, "chunk string, bucket int, first int, low binary, high binary, lens binary")

    def assemble(coded: pa.Table, placed: pa.Table) -> pa.Table:
        columns = ("bucket", "first", "low", "high", "lens")
        blocks = [(first, _wide(low, high), _unpack(lens, np.int32).astype(np.int64)) for _, first, low, high, lens in zip(*(coded.column(c).to_pylist() for c in columns), strict=True)]
        pieces = {bucket: (_wide(low, high), _unpack(lens, np.int64), own, first) for bucket, first, low, high, lens, own in zip(*(placed.column(c).to_pylist() for c in (*columns, "doc_ids")), strict=True)}
        blocks.sort(key=lambda x: x[0])  # places count through the buckets in this order
        n_of = np.concatenate([np.empty(0, np.int64), *(n for _, _, n in blocks)])
        flat = np.concatenate([np.empty(0, np.int64), *(ids for _, ids, _ in blocks)])
        if not pieces or {p[3] for p in pieces.values()} != {len(n_of)}:
            raise RuntimeError("the two passes over the texts saw different chunks; the input must be the same each time it is read")
        in_order = [pieces[k] for k in sorted(pieces, reverse=True)]
        column, counts, own = np.concatenate([p[0] for p in in_order]), np.concatenate([p[1] for p in in_order]), [x for p in in_order for x in p[2]]
        starts = np.cumsum(n_of) - n_of
        ids = ragged(flat, starts[column], n_of[column]).astype(np.int32)
        ends = np.concatenate([[0], np.cumsum(n_of[column])])[np.concatenate([[0], np.cumsum(counts)])]
        return pa.table({"id": pa.array(own, placed.schema.field("doc_ids").type.value_type), "ids": pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(ids))})

    return encoded.groupBy("chunk").cogroup(places.groupBy("chunk")).applyInArrow(assemble, f"id {kind}, ids array<int>").withColumnRenamed("id", id_col)


def _decoding(batches, ids: str, vocabulary: str):
    table = token_bytes(vocabulary_path(vocabulary))
    flat = np.frombuffer(b"".join(table), np.uint8)
    lens = np.array([len(x) for x in table] + [0], np.int64)
    starts = np.cumsum(lens) - lens
    for whole in batches:
        for k in range(0, whole.num_rows, 256):
            b = whole.slice(k, 256)
            col = b.column(ids)
            values = col.flatten().to_numpy().astype(np.int64)
            values = np.where((values >= 0) & (values < len(table)), values, len(table))
            n = lens[values]
            body = ragged(flat, starts[values], n).tobytes()
            ends = np.concatenate([[0], np.cumsum(n)])
            sizes = np.array([0 if x is None else x for x in pa.compute.list_value_length(col).to_pylist()], np.int64)
            at = ends[np.concatenate([[0], np.cumsum(sizes)])]
            decoded = pa.array([body[s:e] for s, e in zip(at[:-1], at[1:], strict=True)], pa.binary())
            yield pa.RecordBatch.from_arrays([*b.columns, decoded], [*b.schema.names, "decoded"])


def _digesting(batches, id_col: str):
    import hashlib

    text = [b"%d" % k for k in range(1 << 16)]
    lens = np.array([len(x) + 1 for x in text], np.int64)
    flat = np.frombuffer(b",".join([*text, b""]), np.uint8)
    starts = np.cumsum(lens) - lens
    for whole in batches:
        for k in range(0, whole.num_rows, 256):
            b = whole.slice(k, 256)
            col = b.column("ids")
            values = col.flatten().to_numpy().astype(np.int64)
            n = lens[values]
            body = ragged(flat, starts[values], n).tobytes()
            sizes = np.array(pa.compute.list_value_length(col).to_pylist(), np.int64)
            at = np.concatenate([[0], np.cumsum(n)])[np.concatenate([[0], np.cumsum(sizes)])]
            of_ids = [hashlib.sha256(body[s : max(s, e - 1)]).hexdigest() for s, e in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
            of_text = [hashlib.sha256(x).hexdigest() for x in b.column("decoded").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(id_col), pa.array(sizes), pa.array(of_ids), pa.array(of_text)], [id_col, "n_tokens", "ids_sha256", "decoded_sha256"])


def decode(encoded: DataFrame, ids: str = "ids", vocabulary: str = VOCABULARY) -> DataFrame:
    """The rows with ``decoded``, the bytes of their ids."""
    fields = [*(f"`{f.name}` {f.dataType.simpleString()}" for f in encoded.schema.fields), "decoded binary"]
    return encoded.mapInArrow(lambda batches: _decoding(batches, ids, vocabulary), ", ".join(fields))


def decoded_digests(encoded: DataFrame, id_col: str = "doc_id", vocabulary: str = VOCABULARY) -> DataFrame:
    """(id, n_tokens, ids_sha256, decoded_sha256) of rows (id, ids) and what they decode to.

    Decoding and digesting share one Python worker: decoded texts go no further than it.
    """
    kind = dict(encoded.dtypes)[id_col]
    return encoded.mapInArrow(lambda batches: _digesting(_decoding(batches, "ids", vocabulary), id_col), f"{id_col} {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
