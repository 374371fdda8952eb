"""Operator 10: quality rules by gradient-boosted trees over document statistics.

One pass counts each text's statistics; trees fitted on labelled rows score
them. Trees are grown on the driver from a bounded sample of labelled statistics
(not texts), with monotonic constraints on chosen features: more symbols, more
repeated lines or windows, or more capitals can never raise a score. Fitted
trees are flat numpy arrays, walked for all rows of a batch at once.

Defined cases: a null or empty text has no words, fails the base rules and is
not kept; a null id is never held out; labels without a document, or documents
with several labels, add what they have; with too few labels of either class the
base rules alone decide. An empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out, slices, texts_of, with_columns
from .words import joined, windows, word_hashes

SYMBOLS = b"#*$%&|<>"
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_digits", "n_marks", "n_distinct"]
#: Sign a feature's effect must keep: -1 never raises the score, 0 free.
FEATURES = {"log_words": 0, "word_length": 0, "symbols": -1, "dup_lines": -1, "repeats": -1, "upper": -1, "digits": 0, "marks": -1, "distinct": 0, "line_words": 0}
_DROP_SPACE = b" \t\n\v\f\r"
_UPPER, _DIGIT, _MARK = b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b"!?"


def _repeated(w: np.ndarray, n: int) -> int:
    """Words covered by five-word windows that the text holds twice or more."""
    if not len(w):
        return 0
    order = np.argsort(w, kind="stable")
    s = w[order]
    same = s[1:] == s[:-1]
    if not same.any():
        return 0
    hit = np.zeros(len(w), bool)
    hit[order[1:][same]] = True
    hit[order[:-1][same]] = True
    step = np.zeros(n + 1, np.int64)
    at = np.flatnonzero(hit)
    np.add.at(step, at, 1)
    np.add.at(step, at + 5, -1)
    return int((np.cumsum(step[:-1]) > 0).sum())


def statistics(texts: list[str]) -> np.ndarray:
    """Counts (columns COUNTS) of whole texts."""
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    buf, bounds = joined(raw)
    hashes, starts, _ = word_hashes(buf, lower=False)
    cut = np.searchsorted(starts, bounds)
    out = np.zeros((len(texts), len(COUNTS)), np.int64)
    for k, (t, b) in enumerate(zip(texts, raw, strict=True)):
        h = hashes[cut[k] : cut[k + 1]]
        n = len(h)
        seen, dup, lines = set(), 0, 0
        for line in b.split(b"\n"):
            if line and not line.isspace():
                lines += 1
                if line in seen:
                    dup += 1
                else:
                    seen.add(line)
        size = len(b)
        spaces = size - len(b.translate(None, _DROP_SPACE))
        out[k] = (n, len(t) - spaces, size - len(b.translate(None, SYMBOLS)), dup, _repeated(windows(h), n), lines, size - len(b.translate(None, _UPPER)), size - len(b.translate(None, _DIGIT)), size - len(b.translate(None, _MARK)), len(np.unique(h)))
    return out


def features(c: np.ndarray) -> np.ndarray:
    """Model inputs (columns FEATURES) from counts."""
    c = c.astype(np.float64)
    words, chars, lines = np.maximum(c[:, 0], 1), np.maximum(c[:, 1], 1), np.maximum(c[:, 5], 1)
    return np.column_stack([np.log1p(c[:, 0]), c[:, 1] / words, c[:, 2] / chars, c[:, 3] / lines, c[:, 4] / words, c[:, 6] / chars, c[:, 7] / chars, c[:, 8] / words, c[:, 9] / words, c[:, 0] / lines])


def base_failed(c: np.ndarray) -> np.ndarray:
    return (c[:, 0] < 10) | (100 * c[:, 4] > 20 * c[:, 0])


class Trees:
    """Boosted trees on logistic loss; flat node arrays, one row a tree."""

    def __init__(self, rounds: int = 60, depth: int = 4, rate: float = 0.2, bins: int = 64, least: int = 8, ridge: float = 1.0):
        self.rounds, self.depth, self.rate, self.bins, self.least, self.ridge = rounds, depth, rate, bins, least, ridge

    def fit(self, x: np.ndarray, y: np.ndarray, signs: list[int]) -> Trees:
        edges = [np.unique(np.quantile(c, np.linspace(0, 1, self.bins + 1)[1:-1])) for c in x.T]
        code = np.column_stack([np.searchsorted(e, c, side="left") for e, c in zip(edges, x.T, strict=True)])
        size = 2 ** (self.depth + 1) - 1
        self.feature = np.full((self.rounds, size), -1, np.int16)
        self.cut = np.zeros((self.rounds, size))
        self.value = np.zeros((self.rounds, size))
        rate_1 = min(max(y.mean(), 1e-6), 1 - 1e-6)
        self.start = float(np.log(rate_1 / (1 - rate_1)))
        score = np.full(len(y), self.start)
        for t in range(self.rounds):
            p = 1 / (1 + np.exp(-score))
            g, h = y - p, np.maximum(p * (1 - p), 1e-12)
            todo = [(0, np.arange(len(y)), -np.inf, np.inf)]
            while todo:
                node, rows, low, high = todo.pop()
                mean = float(np.clip(g[rows].sum() / (h[rows].sum() + self.ridge), low, high))
                self.value[t, node] = mean * self.rate
                best = self._best(code, g, h, rows, signs, low, high) if node < 2**self.depth - 1 else None
                if best is None:
                    score[rows] += mean * self.rate
                    continue
                f, b, left, right = best
                self.feature[t, node], self.cut[t, node] = f, edges[f][b]
                to_left = code[rows, f] <= b
                mid = (left + right) / 2
                lo_hi = {0: ((low, high), (low, high)), 1: ((low, mid), (mid, high)), -1: ((mid, high), (low, mid))}[signs[f]]
                todo += [(2 * node + 1, rows[to_left], *lo_hi[0]), (2 * node + 2, rows[~to_left], *lo_hi[1])]
        return self

    def _best(self, code, g, h, rows, signs, low, high):
        if len(rows) < 2 * self.least:
            return None
        gt, ht = g[rows].sum(), h[rows].sum()
        best, gain = None, 1e-6 + gt * gt / (ht + self.ridge)
        for f, sign in enumerate(signs):
            c = code[rows, f]
            n = np.cumsum(np.bincount(c, minlength=self.bins))[:-1]
            gl, hl = (np.cumsum(np.bincount(c, w[rows], minlength=self.bins))[:-1] for w in (g, h))
            left, right = np.clip(gl / (hl + self.ridge), low, high), np.clip((gt - gl) / (ht - hl + self.ridge), low, high)
            got = gl * gl / (hl + self.ridge) + (gt - gl) ** 2 / (ht - hl + self.ridge)
            got[(n < self.least) | (len(rows) - n < self.least) | (sign * (right - left) < 0)] = -np.inf
            k = int(got.argmax()) if len(got) else -1
            if k >= 0 and got[k] > gain:
                best, gain = (f, k, float(left[k]), float(right[k])), got[k]
        return best

    def score(self, x: np.ndarray) -> np.ndarray:
        """Probability of good quality for each row."""
        total = np.full(len(x), self.start)
        every = np.arange(len(x))
        for t in range(self.rounds):
            node = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                f = self.feature[t, node]
                inner = f >= 0
                node = np.where(inner, 2 * node + 1 + (x[every, np.maximum(f, 0)] > self.cut[t, node]), node)
            total += self.value[t, node]
        return 1 / (1 + np.exp(-total))


def with_statistics(docs: DataFrame, text: str = "text") -> DataFrame:
    """The documents with their counts, which replace columns of the same names."""

    def run(batches):
        for b in slices(batches, text):
            c = statistics(texts_of(b, text))
            yield with_columns(b, {n: pa.array(c[:, k]) for k, n in enumerate(COUNTS)})

    kept = [f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields if f.name not in COUNTS]
    return docs.mapInArrow(run, ", ".join([*kept, *(f"{n} long" for n in COUNTS)]))


def train(docs: DataFrame, labels: DataFrame, max_rows: int = 20_000, id_col: str = "doc_id", text: str = "text") -> Trees | None:
    """Trees from at most ``max_rows`` labelled rows that are not held out, taken by a hash of the id."""
    some = labels.where(F.col("quality").isNotNull() & F.col(id_col).isNotNull() & ~held_out(id_col)).select(id_col, "quality")
    some = some.orderBy(F.xxhash64(id_col), id_col).limit(max_rows)
    rows = docs.select(id_col, text).join(F.broadcast(some), id_col).select("quality", text)
    got = with_statistics(rows, text).select("quality", *COUNTS).toPandas()
    y = got["quality"].to_numpy(np.float64)
    if min((y == 1).sum(), (y == 0).sum()) < 20:
        return None
    order = np.lexsort(got.to_numpy().T)  # the same trees whatever the order of rows
    return Trees().fit(features(got[COUNTS].to_numpy())[order], y[order], list(FEATURES.values()))


def judge(docs: DataFrame, trees: Trees | None, text: str = "text", least: float = 0.5) -> DataFrame:
    """The documents with counts, base_failed, quality_score and kept."""
    shipped = docs.sparkSession.sparkContext.broadcast(trees)

    def run(batches):
        for b in slices(batches, text):
            c = statistics(texts_of(b, text))
            failed = base_failed(c)
            p = shipped.value.score(features(c)) if shipped.value is not None else np.ones(len(c))
            yield with_columns(b, {n: pa.array(c[:, k]) for k, n in enumerate(COUNTS)} | {"base_failed": pa.array(failed), "quality_score": pa.array(p), "kept": pa.array(~failed & (p >= least))})

    extra = {**{n: "long" for n in COUNTS}, "base_failed": "boolean", "quality_score": "double", "kept": "boolean"}
    kept = [f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields if f.name not in extra]
    return docs.mapInArrow(run, ", ".join([*kept, *(f"{n} {t}" for n, t in extra.items())]))
