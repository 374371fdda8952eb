"""Operator 7: token counts that follow edits.

A document's pre-tokens stand in blocks under a segment tree of sums (code
points and tokens). An edit finds its place by descending the code-point sums,
re-splits from the last boundary that the edit can't have moved, stops at the
first old boundary met again behind it, re-encodes those pre-tokens only, and
corrects the sums on the way up. Every other pre-token keeps its count.

A boundary is safe if it lies two code points or more before the edit: no
alternative of the pattern looks further than one code point past a match, or
two past an apostrophe. Splitting has no look-behind, so from a common boundary
on equal text splits alike.

Trees travel as packed arrays of lengths and counts, so they can be stored with
the documents. Defined cases: a null text is empty; an edit's start and length
are clipped to the text; a null replacement deletes; edits apply in the order
given; null or empty edits change nothing; repeated rows are counted each; an
empty table gives an empty result.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .bpe import WordCache, _FAST, _slow, encoding, is_plain, pattern_for, vocabulary_path
from .common import slices, texts_of, with_columns

VOCABULARY, BLOCK = "byte_bpe_50k.tiktoken", 64
EDITS = "array<struct<start:bigint,length:bigint,replacement:string>>"


def word_counter(vocabulary: str = VOCABULARY) -> WordCache:
    ranks = encoding(vocabulary_path(vocabulary))
    return WordCache(lambda w: len(ranks.encode_ordinary(w)))


class CountTree:
    """Pre-token lengths and token counts in blocks, with sums over blocks."""

    def __init__(self, text: str, lengths: list[int], counts: list[int], counter: WordCache):
        self.text, self.counter, self.plain, self.re_encoded = text, counter, None, 0
        self._build(lengths, counts)

    @classmethod
    def of(cls, text: str, counter: WordCache) -> CountTree:
        words = pattern_for(text).findall(text)
        return cls(text, [len(w) for w in words], [counter[w] for w in words], counter)

    def _build(self, lengths: list[int], counts: list[int]) -> None:
        cut = range(0, max(1, len(lengths)), BLOCK)
        self.lengths = [lengths[k : k + BLOCK] for k in cut]
        self.counts = [counts[k : k + BLOCK] for k in cut]
        self.size = 1 << (len(self.lengths) - 1).bit_length()
        self.chars, self.tokens = [0] * (2 * self.size), [0] * (2 * self.size)
        for k in range(len(self.lengths)):
            self.chars[self.size + k], self.tokens[self.size + k] = sum(self.lengths[k]), sum(self.counts[k])
        for k in range(self.size - 1, 0, -1):
            self.chars[k], self.tokens[k] = self.chars[2 * k] + self.chars[2 * k + 1], self.tokens[2 * k] + self.tokens[2 * k + 1]

    @property
    def n_tokens(self) -> int:
        return self.tokens[1]

    def _renew(self, block: int) -> None:
        k = self.size + block
        self.chars[k], self.tokens[k] = sum(self.lengths[block]), sum(self.counts[block])
        while k > 1:
            k //= 2
            self.chars[k], self.tokens[k] = self.chars[2 * k] + self.chars[2 * k + 1], self.tokens[2 * k] + self.tokens[2 * k + 1]

    def _block_at(self, place: int) -> tuple[int, int]:
        """The block that holds a code point (the last block at the end), and where it starts."""
        k, start = 1, 0
        while k < self.size:
            k *= 2
            if place >= start + self.chars[k] and self.chars[k + 1]:
                start += self.chars[k]
                k += 1
        return k - self.size, start

    def edit(self, start: int, length: int, replacement: str) -> None:
        start = min(max(start, 0), len(self.text))
        length = min(max(length, 0), len(self.text) - start)
        new = "".join((self.text[:start], replacement, self.text[start + length :]))
        if self.plain is None:
            self.plain = is_plain(self.text)
        self.plain = self.plain and is_plain(replacement)
        match = (_FAST if self.plain else _slow()).match
        # The last boundary at least two code points before the edit.
        first, at = self._block_at(max(0, start - 2))
        k = 0
        while k < len(self.lengths[first]) and at + self.lengths[first][k] <= start - 2:
            at += self.lengths[first][k]
            k += 1
        # Old boundaries from there on, as (block, index) of the pre-token that starts at each.
        last, j, old = first, k, at
        shift, lengths, counts, now = len(replacement) - length, [], [], at
        while True:
            while old < start + length or old + shift < now:
                while j == len(self.lengths[last]) and last + 1 < len(self.lengths):
                    last, j = last + 1, 0
                if j == len(self.lengths[last]):
                    break
                old += self.lengths[last][j]
                j += 1
            if old >= start + length and old + shift == now or now == len(new):
                break
            end = match(new, now).end()
            lengths.append(end - now)
            counts.append(self.counter[new[now:end]])
            now = end
        if now == len(new):
            last, j = len(self.lengths) - 1, len(self.lengths[-1])
        self.re_encoded += len(lengths)
        head, tail = slice(None, k), slice(j, None)
        self.text = new
        merged = self.lengths[first][head] + lengths + self.lengths[last][tail], self.counts[first][head] + counts + self.counts[last][tail]
        for b in range(first + 1, last + 1):
            self.lengths[b], self.counts[b] = [], []
            self._renew(b)
        self.lengths[first], self.counts[first] = merged
        self._renew(first)
        if len(self.lengths[first]) > 8 * BLOCK:
            self._build([x for b in self.lengths for x in b], [x for b in self.counts for x in b])

    def packed(self) -> bytes:
        a = np.array([[x for b in self.lengths for x in b], [x for b in self.counts for x in b]], np.uint32)
        return zlib.compress(a.T.astype(np.uint16 if not a.size or a.max() < 1 << 16 else np.uint32).T.tobytes() + bytes([2 if not a.size or a.max() < 1 << 16 else 4]), 1)

    @classmethod
    def unpacked(cls, text: str, packed: bytes, counter: WordCache) -> CountTree:
        raw = zlib.decompress(packed)
        a = np.frombuffer(raw[:-1], np.uint16 if raw[-1] == 2 else np.uint32)
        half = len(a) // 2
        return cls(text, a[:half].tolist(), a[half:].tolist(), counter)


def _fields(df: DataFrame, extra: dict[str, str]) -> str:
    return ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields if f.name not in extra), *(f"{k} {v}" for k, v in extra.items())])


def build_trees(docs: DataFrame, text: str = "text", vocabulary: str = VOCABULARY) -> DataFrame:
    """The documents with n_tokens and their packed tree."""

    def run(batches):
        counter = word_counter(vocabulary)
        for b in slices(batches, text):
            trees = [CountTree.of(t, counter) for t in texts_of(b, text)]
            yield with_columns(b, {"n_tokens": pa.array([t.n_tokens for t in trees], pa.int64()), "tree": pa.array([t.packed() for t in trees], pa.binary())})

    return docs.mapInArrow(run, _fields(docs, {"n_tokens": "long", "tree": "binary"}))


def apply_edits(docs: DataFrame, text: str = "text", tree: str = "tree", edits: str = "edits", vocabulary: str = VOCABULARY) -> DataFrame:
    """Documents whose column ``edits`` (array of start, length, replacement) has been applied:
    text and tree renewed, n_tokens corrected, re_encoded pre-tokens counted."""

    def run(batches):
        counter = word_counter(vocabulary)
        for b in slices(batches, text):
            done = []
            for t, packed, todo in zip(texts_of(b, text), b.column(tree).to_pylist(), b.column(edits).to_pylist(), strict=True):
                own = CountTree.unpacked(t, packed, counter) if packed is not None else CountTree.of(t, counter)
                for e in todo or ():
                    if e is not None and e["start"] is not None:
                        own.edit(e["start"], e["length"] or 0, e["replacement"] or "")
                done.append(own)
            yield with_columns(b, {text: pa.array([d.text for d in done], pa.string()), tree: pa.array([d.packed() for d in done], pa.binary()), "n_tokens": pa.array([d.n_tokens for d in done], pa.int64()), "re_encoded": pa.array([d.re_encoded for d in done], pa.int64())})

    return docs.mapInArrow(run, _fields(docs, {text: "string", tree: "binary", "n_tokens": "long", "re_encoded": "long"}))


def attach_edits(docs: DataFrame, edits: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Documents with their edits (id, seq, start, length, replacement) as an array in order of seq."""
    per = edits.groupBy(id_col).agg(F.sort_array(F.collect_list(F.struct("seq", "start", "length", "replacement"))).alias("_e"))
    per = per.select(id_col, F.transform("_e", lambda e: F.struct(e["start"].cast("long").alias("start"), e["length"].cast("long").alias("length"), e["replacement"].alias("replacement"))).alias("edits"))
    return docs.join(per, id_col, "left")


def sample_edits(id_col: str = "doc_id", text: str = "text") -> Column:
    """Three edits of every text, placed by a hash of its id: an insertion, a deletion, a replacement."""
    n = F.coalesce(F.char_length(text), F.lit(0)).cast("long")
    place = lambda seed: F.pmod(F.crc32(F.concat_ws("/", F.lit(seed), F.col(id_col)).cast("binary")), n + 1).cast("long")
    parts = [("a", 0, " and 12 more's"), ("b", 12, ""), ("c", 5, "Ünïcode 42!\n")]
    return F.array(*(F.struct(place(s).alias("start"), F.lit(k).cast("long").alias("length"), F.lit(r).alias("replacement")) for s, k, r in parts))
