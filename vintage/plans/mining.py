"""Near copies of dated versions in a training corpus: retrieval, confirmation, attribution."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distance import bounded
from ..functions.text import runs_of
from ..functions.timegrid import LAST_MONTH
from ..sources.tables import stored

K1, B = 1.2, 0.75
#: Query terms that one scan of the corpus takes along, in rows; more queries make several scans.
BROADCAST_TERMS = 2_000_000
#: Documents scored side by side in a task, and pairs that one task of distances is given.
SCORED_AT_ONCE, PAIRS_A_TASK = 128, 500
_CONTENTS = "doc_id long, length int, terms array<string>, tfs array<int>"


class Index:
    """An index dealt by documents: ``contents`` (doc_id, length, terms, tfs).

    No row belongs to one term, so a term that every document holds is no hot key.
    """

    def __init__(self, contents: DataFrame):
        self.contents = contents

    def postings(self) -> DataFrame:
        """(term, doc_id, tf), one row each."""
        each = F.explode(F.arrays_zip(F.col("terms").alias("term"), F.col("tfs").alias("tf")))
        return self.contents.select("doc_id", each.alias("_p")).select("_p.term", "doc_id", "_p.tf")


def _frequencies(occurring: DataFrame, queries: DataFrame) -> DataFrame:
    """(term, df, length) of the queries' terms; the null term stands for all documents and sums their lengths.

    A task counts its documents first, so a term costs a row a task in the shuffle.
    """
    asked = queries.select("term").distinct()
    asked = asked.union(asked.sparkSession.createDataFrame([(None,)], "term string")).withColumnRenamed("term", "_asked")
    asked = F.broadcast(asked) if asked.limit(BROADCAST_TERMS + 1).count() <= BROADCAST_TERMS else asked
    met = occurring.join(asked, F.col("term").eqNullSafe(F.col("_asked")), "left_semi")
    return stored(met.groupBy("term").agg(F.count(F.lit(1)).alias("df"), F.sum("length").alias("length")))


def _with_all(distinct_terms: Column) -> Column:
    return F.explode(F.concat(distinct_terms, F.array(F.lit(None).cast("string")))).alias("term")


def _counted(doc: np.ndarray, codes: np.ndarray, of: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (document, code) in that order, with how often each stands."""
    key, tf = np.unique(doc.astype(np.int64) * of + codes, return_counts=True)
    return key // of, key % of, tf


def _worded(corpus: DataFrame, toks: str) -> DataFrame:
    """(doc_id, toks); a document without words counts as one of no length."""
    return corpus.select(F.col("doc_id").cast("long"), F.coalesce(F.col(toks), F.array().cast("array<string>")).alias("toks"))


def term_counts(corpus: DataFrame, toks: str = "toks") -> DataFrame:
    """(doc_id, length, terms, tfs) of each document, where it lies."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _small(batches, "toks"):
            words = b.column("toks")
            sizes = pc.fill_null(pc.list_value_length(words), 0).to_numpy()
            coded = pc.dictionary_encode(words.flatten())
            doc, code, tf = _counted(np.repeat(np.arange(len(sizes)), sizes), coded.indices.to_numpy(), max(1, len(coded.dictionary)))
            ends = pa.array(np.concatenate([[0], np.cumsum(np.bincount(doc, minlength=len(sizes)))]).astype(np.int32))
            lists = (pa.ListArray.from_arrays(ends, x) for x in (coded.dictionary.take(pa.array(code)), pa.array(tf, pa.int32())))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(sizes, pa.int32()), *lists], ["doc_id", "length", "terms", "tfs"])

    return _worded(corpus, toks).mapInArrow(run, _CONTENTS)


def build_index(corpus: DataFrame, toks: str = "toks") -> Index:
    return Index(stored(term_counts(corpus, toks)))


def query_terms(versions: DataFrame, n_words: int = 512, toks: str = "toks") -> DataFrame:
    """(topic_id, term, qtf) of each topic's query: its first words at the dump's date."""
    return versions.select("topic_id", F.explode(F.slice(toks, 1, n_words)).alias("term")).groupBy("topic_id", "term").agg(F.count(F.lit(1)).alias("qtf"))


def _small(batches: Iterator[pa.RecordBatch], words: str, limit: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Batches cut where their lists of words reach ``limit`` entries or SCORED_AT_ONCE rows."""
    for b in batches:
        sizes = pc.fill_null(pc.list_value_length(b.column(words)), 0).to_pylist()
        start = total = 0
        for i, n in enumerate(sizes):
            if i > start and (total + n > limit or i - start >= SCORED_AT_ONCE):
                yield b.slice(start, i - start)
                start, total = i, 0
            total += n
        if start < len(sizes):
            yield b.slice(start)


class _Queries:
    """The queries as sparse rows by term: topics, and their weights without the document's part."""

    def __init__(self, rows: pa.Table, totals: tuple[int, float], k: int):
        n, self.mean = totals[0], totals[1] or 1.0
        topic = rows.column("topic_id").to_numpy()
        coded = pc.dictionary_encode(rows.column("term").combine_chunks())
        self.topics, place = np.unique(topic, return_inverse=True)
        order = np.argsort(coded.indices.to_numpy(), kind="stable")
        df, qtf = rows.column("df").to_numpy().astype(np.float64), rows.column("qtf").to_numpy().astype(np.float64)
        self.terms, self.k = coded.dictionary, k
        self.place, self.weight = place[order], (qtf * np.log(1 + (n - df + 0.5) / (df + 0.5)))[order]
        self.first = np.searchsorted(coded.indices.to_numpy()[order], np.arange(len(self.terms) + 1))

    def best(self, parts: Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]) -> pa.RecordBatch:
        """The k best documents of each topic among all (ids, lengths, document, code, tf) of a task."""
        at, score, doc = np.zeros(0, np.int64), np.zeros(0), np.zeros(0, np.int64)
        least = np.full(len(self.topics), 1e-6)
        for ids, lengths, row, code, tf in parts:
            part = tf * (K1 + 1) / (tf + K1 * (1 - B + B * lengths[row] / self.mean))
            table = np.zeros((len(ids), len(self.topics)))
            for r, c, x in zip(row.tolist(), code.tolist(), part.tolist(), strict=True):
                span = slice(self.first[c], self.first[c + 1])
                table[r, self.place[span]] += self.weight[span] * x
            table = np.round(table, 6)  # so that equal documents tie in any order of sums
            r, t = np.nonzero(table >= least)
            at, score, doc = np.concatenate([at, t]), np.concatenate([score, table[r, t]]), np.concatenate([doc, ids[r]])
            if len(at) > 4 * self.k * len(self.topics):
                at, score, doc, least = self._cut(at, score, doc, least)
        at, score, doc, _ = self._cut(at, score, doc, least)
        return pa.RecordBatch.from_arrays([pa.array(self.topics[at], pa.int64()), pa.array(doc, pa.int64()), pa.array(score)], ["topic_id", "doc_id", "score"])

    def _cut(self, at, score, doc, least):
        order = np.lexsort((doc, -score, at))
        at, score, doc = at[order], score[order], doc[order]
        rank = np.arange(len(at)) - np.searchsorted(at, at)
        keep = rank < self.k
        least = least.copy()
        last = rank == self.k - 1
        least[at[last]] = score[last]
        return at[keep], score[keep], doc[keep], least


def _ranked(scores: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("topic_id").orderBy(F.desc("score"), "doc_id")
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("topic_id", "doc_id", "rank", F.round("score", 6).alias("score"))


def _search(source: DataFrame, words: str, decode, queries: DataFrame, frequencies: DataFrame, k: int) -> DataFrame:
    """Scores every document where it lies; a task hands on k documents a topic.

    The queries' terms travel to the tasks, in blocks of topics of at most about
    BROADCAST_TERMS rows; each block is one pass over the source.
    """
    spark = source.sparkSession
    asked = stored(queries.join(frequencies, "term").select(F.col("topic_id").cast("long"), "term", "qtf", "df"))
    blocks = max(1, -(-asked.count() // BROADCAST_TERMS))
    n, length = frequencies.where("term is null").select("df", "length").first() or (0, 0)
    found = []
    for block in range(blocks):
        mine = asked.where(F.pmod(F.xxhash64("topic_id"), F.lit(blocks)) == block)
        shipped = spark.sparkContext.broadcast(_Queries(mine.toArrow(), (n, (length or 0) / n if n else 1.0), k))

        def run(batches: Iterator[pa.RecordBatch], shipped=shipped) -> Iterator[pa.RecordBatch]:
            yield shipped.value.best(decode(b, shipped.value.terms) for b in _small(batches, words))

        found.append(source.mapInArrow(run, "topic_id long, doc_id long, score double"))
    every = found[0]
    for part in found[1:]:
        every = every.union(part)
    return _ranked(every, k)


def _of_words(b: pa.RecordBatch, terms: pa.Array):
    words = b.column("toks")
    sizes = pc.fill_null(pc.list_value_length(words), 0).to_numpy()
    code = pc.index_in(words.flatten(), value_set=terms)
    known = pc.is_valid(code).to_numpy(zero_copy_only=False)
    doc = np.repeat(np.arange(len(sizes)), sizes)[known]
    return b.column("doc_id").to_numpy(), sizes, *_counted(doc, pc.drop_null(code).to_numpy(), max(1, len(terms)))


def _of_contents(b: pa.RecordBatch, terms: pa.Array):
    words = b.column("terms")
    code = pc.index_in(words.flatten(), value_set=terms)
    known = pc.is_valid(code).to_numpy(zero_copy_only=False)
    doc = np.repeat(np.arange(b.num_rows), pc.list_value_length(words).to_numpy())[known]
    return b.column("doc_id").to_numpy(), b.column("length").to_numpy(), doc, pc.drop_null(code).to_numpy(), b.column("tfs").flatten().to_numpy()[known]


def top_k(index: Index, queries: DataFrame, k: int = 10) -> DataFrame:
    """(topic_id, doc_id, rank, score) by an index, whose rows stay where they are. BM25, ties by id."""
    frequencies = _frequencies(index.contents.select(_with_all(F.col("terms")), "length"), queries)
    return _search(index.contents, "terms", _of_contents, queries, frequencies, k)


def top_k_scan(corpus: DataFrame, queries: DataFrame, k: int = 10, toks: str = "toks") -> DataFrame:
    """The same from the words themselves: two passes over the corpus, no index, no document in a shuffle."""
    words = _worded(corpus, toks)
    frequencies = _frequencies(words.select(_with_all(F.array_distinct("toks")), F.size("toks").alias("length")), queries)
    return _search(words, "toks", _of_words, queries, frequencies, k)


def within(length: int, threshold: float, inclusive: bool = False) -> int:
    """The largest whole distance below (or at) threshold * length; thresholds have four places at most."""
    parts = round(threshold * 10_000) * length
    return parts // 10_000 if inclusive else -(-parts // 10_000) - 1


class History:
    """A topic's versions in Python: texts by their first month, and how far neighbours can be apart."""

    def __init__(self, toks: list[str], tail: str, edits: list[dict]):
        self.starts = sorted({0, *(e["month"] for e in edits)})
        self.spans = [(f, t - 1) for f, t in zip(self.starts, [*self.starts[1:], LAST_MONTH + 1], strict=True)]
        words, self.texts, self.steps, at = list(toks), [], [], 0
        for f in self.starts:
            step = 0
            while at < len(edits) and edits[at]["month"] <= f:
                e = edits[at]
                if words[e["pos"]] != e["token"]:
                    step += max(len(words[e["pos"]]), len(e["token"]))
                    words[e["pos"]] = e["token"]
                at += 1
            self.texts.append(" ".join([*words, tail] if tail else words))
            self.steps.append(step)

    def matches(self, doc: str, most: int) -> tuple[list[tuple[int, int, int]], dict[str, int]]:
        """(version_from, version_to, distance) of the versions within ``most``, and what that cost.

        A version differs from its neighbour in a few replaced words, which bound
        the distance between them. So one distance, to the middle version, with
        a bound widened by the way to the farthest version, clears a document that
        matches none; and where it matches, each distance bounds the next.
        """
        cost = {"versions": len(self.texts), "gated": 0, "distances": 0}
        out = []
        fits = [k for k, t in enumerate(self.texts) if abs(len(t) - len(doc)) <= most]
        cost["gated"] = len(self.texts) - len(fits)
        if not fits:
            return out, cost
        way = np.cumsum(self.steps)
        mid = fits[len(fits) // 2]
        reach = most + int(max(way[fits[-1]] - way[mid], way[mid] - way[fits[0]]))
        cost["distances"] = 1
        d = bounded(doc, self.texts[mid], reach, reach)
        if d is None:
            return out, cost
        known = {mid: (d, d)}  # least and greatest possible distance
        for k in sorted(fits, key=lambda k: abs(k - mid)):
            if k != mid:
                near = min(known, key=lambda j: abs(j - k))
                apart = int(abs(way[k] - way[near]))
                low, high = known[near][0] - apart, known[near][1] + apart
                if low <= most:
                    cost["distances"] += 1
                    d = bounded(doc, self.texts[k], min(most, high), min(most, high))
                    low, high = (most + 1, max(high, most + 1)) if d is None else (d, d)
                known[k] = low, high
            if known[k][0] <= most:
                out.append((*self.spans[k], known[k][0]))
        return sorted(out), cost


_FOUND = "topic_id long, doc_id long, length int, found array<struct<version_from:int,version_to:int,dist:int>>, versions int, gated int, distances int"


def compare_versions(hits: DataFrame, corpus: DataFrame, packed: DataFrame, threshold: float = 0.2, inclusive: bool = False) -> DataFrame:
    """Each hit's document against every version of its topic, with what that cost.

    ``packed``: topics with their whole history in a row, so a hit travels with two
    texts and a list of edits, not with a text for each version. Distances of
    pairs differ by a factor of a hundred, so hits are dealt out evenly before;
    equal documents of a topic are compared once.
    """
    hits = stored(hits.select(F.col("topic_id").cast("long"), F.col("doc_id").cast("long")))
    n = hits.count()
    texts = corpus.select(F.col("doc_id").cast("long"), "text").join(F.broadcast(hits.select("doc_id").distinct()) if n <= BROADCAST_TERMS else hits.select("doc_id").distinct(), "doc_id", "left_semi")
    met = hits.join(texts, "doc_id").join(packed.select(F.col("topic_id").cast("long"), "toks", "tail", "edits"), "topic_id")
    tasks = max(hits.sparkSession.sparkContext.defaultParallelism * 2, -(-n // PAIRS_A_TASK))
    dealt = met.repartition(tasks, "topic_id", F.xxhash64("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        done: dict = {}
        for b in batches:
            for lo in range(0, b.num_rows, 32):
                out = []
                for r in b.slice(lo, 32).to_pylist():
                    key = r["topic_id"], r["text"]
                    free = key in done
                    if not free:
                        done = done if len(done) < 64 else {}
                        doc = r["text"] or ""
                        done[key] = History(r["toks"], r["tail"], r["edits"]).matches(doc, within(len(doc), threshold, inclusive))
                    found, cost = done[key]
                    out.append({"topic_id": r["topic_id"], "doc_id": r["doc_id"], "length": len(r["text"] or ""), "found": [dict(zip(("version_from", "version_to", "dist"), x, strict=True)) for x in found], "versions": cost["versions"], "gated": cost["gated"], "distances": 0 if free else cost["distances"]})
                yield pa.RecordBatch.from_pylist(out, schema=schema)

    span = pa.struct([("version_from", pa.int32()), ("version_to", pa.int32()), ("dist", pa.int32())])
    schema = pa.schema([("topic_id", pa.int64()), ("doc_id", pa.int64()), ("length", pa.int32()), ("found", pa.list_(span)), ("versions", pa.int32()), ("gated", pa.int32()), ("distances", pa.int32())])
    return dealt.mapInArrow(run, _FOUND)


def edit_match(compared: DataFrame) -> DataFrame:
    """Pairs within the distance: (topic_id, doc_id, version_from, version_to, dist, norm)."""
    each = compared.select("topic_id", "doc_id", "length", F.inline("found"))
    norm = F.coalesce(F.col("dist") / F.nullif(F.col("length"), F.lit(0)), F.lit(0.0))
    return each.select("topic_id", "doc_id", "version_from", "version_to", "dist", norm.alias("norm"))


def costs(compared: DataFrame) -> DataFrame:
    """One row: hits, pairs of a hit and a version, those that lengths rule out, distances taken, pairs matched."""
    total = lambda c: F.sum(c).cast("long")
    return compared.agg(F.count(F.lit(1)).alias("hits"), total("versions").alias("pairs"), total("gated").alias("ruled_out_by_length"), total("distances").alias("distances"), total(F.size("found")).alias("matched"))


def attribute(matches: DataFrame, ties: str = "all", measure: str = "dist") -> DataFrame:
    """(topic_id, doc_id, month_ix, weight): each matched document's nearest months.

    ``ties``: ``all`` counts every nearest month once, ``split`` shares one count
    among them, ``earliest`` and ``latest`` keep one.
    """
    keys = ["topic_id", "doc_id"]
    least = matches.groupBy(*keys).agg(F.min(measure).alias("_least"))
    best = matches.join(least, keys).where(F.col(measure) == F.col("_least"))
    spread = best.select(*keys, F.explode(F.sequence("version_from", "version_to")).alias("month_ix")).distinct()
    if ties == "split":
        return spread.withColumn("weight", 1.0 / F.count(F.lit(1)).over(Window.partitionBy(*keys)))
    if ties in ("earliest", "latest"):
        pick = F.min if ties == "earliest" else F.max
        spread = spread.groupBy(*keys).agg(pick("month_ix").alias("month_ix"))
    return spread.withColumn("weight", F.lit(1.0))


def ngram_match(hits: DataFrame, corpus: DataFrame, versions: DataFrame, n: int = 5, threshold: float = 0.5) -> DataFrame:
    """Hits by shared n-grams: (topic_id, doc_id, version_from, version_to, share, dist), dist = 1 - share.

    Grams are numbers: 64-bit hashes of their words. Each text's grams are taken once.
    """
    def grams(text: str) -> Column:
        return F.array_distinct(runs_of(F.split(text, " "), n, lambda ws: F.xxhash64(*ws)))

    texts = corpus.join(hits.select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", grams("text").alias("d"))
    tasks = max(2 * hits.sparkSession.sparkContext.defaultParallelism, -(-hits.count() // PAIRS_A_TASK))
    docs = hits.select("topic_id", "doc_id").join(texts, "doc_id").repartition(tasks, "topic_id")
    vers = stored(versions.select("topic_id", "version_from", "version_to", grams("text").alias("v")))
    share = F.size(F.array_intersect("d", "v")) / F.nullif(F.size("d"), F.lit(0))
    met = docs.join(vers, "topic_id").select("topic_id", "doc_id", "version_from", "version_to", share.alias("share"))
    kept = met.where(F.col("share") >= threshold)
    return kept.select("topic_id", "doc_id", "version_from", "version_to", "share", F.round(1 - F.col("share"), 9).alias("dist"))


def month_sets(attributed: DataFrame) -> DataFrame:
    return attributed.groupBy("topic_id", "doc_id").agg(F.array_sort(F.collect_set("month_ix")).alias("months"))


def histogram(attributed: DataFrame, grid: DataFrame, by: list[str] | None = None) -> DataFrame:
    """(by..., month_ix, n): matched documents a month; months without any stand at zero."""
    by = by or []
    counts = attributed.groupBy(*by, "month_ix").agg(F.sum("weight").alias("n"))
    if not by:
        frame = grid
    else:
        frame = attributed.select(*by).distinct().crossJoin(F.broadcast(grid))  # classes times the calendar
    return frame.join(counts, [*by, "month_ix"], "left").withColumn("n", F.coalesce("n", F.lit(0.0)))


def static_inclusion(ppl: DataFrame, threshold: float) -> DataFrame:
    """Membership-style baseline: is a version in the corpus at all? (model, included, versions)."""
    return ppl.groupBy("model").agg(F.count_if(F.col("ppl") < threshold).alias("included"), F.count(F.lit(1)).alias("versions"))


def exact_inclusion(versions: DataFrame, corpus: DataFrame) -> DataFrame:
    """Versions whose very text is in the corpus, by hash."""
    known = corpus.select(F.sha2("text", 256).alias("h")).distinct()
    return versions.withColumn("h", F.sha2("text", 256)).join(known, "h", "left_semi").drop("h")
