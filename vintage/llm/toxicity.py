"""Operator 5: toxicity by a weighted finite-state grammar over clauses.

A lexicon reads a clause word by word and writes a symbol for each: insult,
threat, target, negation, report or other. Transducers rewrite that tape one
after another: negation marks insults and threats within its reach, reported
speech marks those behind a verb of saying, target remembers that someone is
addressed, and two acceptors, of insults and of threats, each take one hit and
weigh it by its marks. They are tables of arcs, composed into one automaton
when the module loads; a clause's weight is that of its best path, found in one
walk, and a document's score the noisy-or of its clauses. So a word alone scores
nothing: a negation just before it or reported speech takes most of its weight
away, an addressed target adds to it, and a threat without one is a mere mention.

The word classes other than insults are short fixed lists. Insults, words and
stems, are learned from labelled rows: a form is taken if it occurs in far more
toxic than clean documents than chance allows, and a stem at the longest length
that keeps nine tenths of its documents. Learning reads at most ``max_rows`` labelled rows of
each class, none of them held out, and never language, source or id.

Texts are searched once by an Aho-Corasick automaton of all classes; only
clauses with a hit are walked. Defined cases: a null or empty text scores 0.01;
repeated rows score alike; without toxic labels only the fixed threats score; an
empty table gives an empty result.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out, slices, texts_of, with_columns

#: Fixed word lists by class, in the languages of the tables.
THREATS = [
    "kill", "hurt", "destroy", "murder", "strangle", "stab", "shoot", "burn", "crush", "punch",
    "töten", "umbringen", "erschießen", "verprügeln", "schlagen", "tuer", "frapper", "étrangler", "égorger", "matar", "golpear", "asesinar", "quemar",
]
TARGETS = [
    "you", "your", "yours", "yourself", "they", "them", "their", "him", "her", "du", "dich", "dir", "dein", "ihr", "euch", "euer",
    "tu", "toi", "te", "vous", "votre", "usted", "ustedes", "vosotros", "ti",
]
NEGATIONS = [
    "not", "never", "no", "nobody", "neither", "nor", "without", "isn't", "aren't", "wasn't", "don't", "doesn't", "didn't", "won't", "can't",
    "nicht", "kein", "keine", "keinen", "nie", "niemals", "ohne", "pas", "jamais", "aucun", "sans", "nunca", "jamás", "ningún", "sin",
]
REPORTS = [
    "said", "says", "saying", "wrote", "writes", "called", "calls", "quoted", "quotes", "claimed", "claims", "told", "reported",
    "sagte", "sagt", "schrieb", "schreibt", "nannte", "zitierte", "disait", "dit", "écrivait", "écrit", "appelait", "dijo", "dice", "escribió", "llamó",
]

CLAUSE_END = re.compile(r"[.!?;:\n]+")
WORD = re.compile(r"[^\W\d_]+(?:'[^\W\d_]+)?")
REACH = 3  # words that a negation stays in force
NEGATED, REPORTED, TARGETED, UNARMED = 0.25, 0.5, 0.1, 0.2
STEM = range(3, 8)


HITS = ("insult", "threat")
#: Marks that transducers leave on a hit, and what each is worth.
MARKS = {"-": NEGATED, '"': REPORTED}


class Transducer:
    """Arcs {state: {symbol: [(next state, symbol written, whether the hit is taken, factor)]}} from ``start``.

    A symbol that a state doesn't list is copied, and the state stays.
    """

    def __init__(self, start, arcs: dict):
        self.start, self.arcs = start, arcs

    def step(self, state, symbol: str) -> list[tuple]:
        return self.arcs.get(state, {}).get(symbol) or [(state, symbol, False, 1.0)]


def _forms(kinds=HITS) -> list[str]:
    """Hits with every set of marks, in the order that the transducers write them."""
    return [k + m for k in kinds for m in ("", "-", '"', '-"')]


def negating(reach: int = REACH) -> Transducer:
    """Marks hits among the ``reach`` words behind a negation; the state counts the words left."""
    arcs: dict = {}
    for left in range(reach + 1):
        rest = max(0, left - 1)
        own = {s: [(rest, s, False, 1.0)] for s in ("other", "target", "report")}
        own |= {s: [(rest, s + "-" if left else s, False, 1.0)] for s in HITS}
        arcs[left] = own | {"negation": [(reach, "negation", False, 1.0)]}
    return Transducer(0, arcs)


def reporting() -> Transducer:
    """Marks hits behind a verb of saying."""
    quoted = {s: [(True, s + '"', False, 1.0)] for k in HITS for s in (k, k + "-")}
    return Transducer(False, {False: {"report": [(True, "report", False, 1.0)]}, True: quoted})


def targeting() -> Transducer:
    """Remembers whether someone is addressed anywhere in the clause."""
    return Transducer(False, {False: {"target": [(True, "target", False, 1.0)]}})


def accepting(kind: str) -> Transducer:
    """Takes one hit of a kind, or none so far; a mark on it is a factor."""
    taken = {s: [(None, s, False, 1.0), (kind, s, True, math.prod(f for m, f in MARKS.items() if m in s))] for s in _forms((kind,))}
    return Transducer(None, {None: taken})


def either(one: Transducer, other: Transducer) -> Transducer:
    """The union of two acceptors that share their start."""
    return Transducer(one.start, {one.start: {**one.arcs[one.start], **other.arcs[other.start]}})


def compose(first: Transducer, then: Transducer, symbols: list[str]) -> Transducer:
    """One transducer that reads ``symbols`` as ``first`` does and writes what ``then`` makes of it."""
    start = (first.start, then.start)
    arcs: dict = {}
    todo = [start]
    while todo:
        at = todo.pop()
        if at in arcs:
            continue
        arcs[at] = {}
        for s in symbols:
            out = [((p, q), y, took or takes, f * g) for p, x, took, f in first.step(at[0], s) for q, y, takes, g in then.step(at[1], x)]
            arcs[at][s] = out
            todo += [n for n, *_ in out]
    return Transducer(start, arcs)


SYMBOLS = ["other", "negation", "report", "target", *HITS]


class Automaton:
    """The composed grammar with numbered states: arcs[state][symbol] = ((next, taken, factor), ...)."""

    def __init__(self):
        whole = negating()
        for then in (reporting(), targeting(), either(accepting("insult"), accepting("threat"))):
            whole = compose(whole, then, SYMBOLS)
        states = sorted(whole.arcs, key=repr)
        number = {s: k for k, s in enumerate(states)}
        self.start = number[whole.start]
        self.arcs = [{x: tuple((number[n], t, f) for n, _, t, f in whole.arcs[s][x]) for x in SYMBOLS} for s in states]
        self.final = [(s[0][1], s[1]) for s in states]  # whether a target was seen, kind of hit taken

    def weight(self, tape) -> float:
        """Weight of the best path over (symbol, lexical weight) pairs."""
        alive = {self.start: 1.0}
        for symbol, w in tape:
            after: dict[int, float] = {}
            for state, so_far in alive.items():
                for n, taken, factor in self.arcs[state][symbol]:
                    v = so_far * factor * w if taken else so_far
                    if v > after.get(n, 0.0):
                        after[n] = v
            alive = after
        return max(self._ended(state, v) for state, v in alive.items())

    def _ended(self, state: int, v: float) -> float:
        target, kind = self.final[state]
        if kind == "insult":
            return v + TARGETED * (1 - v) if target else v
        if kind == "threat":
            return v if target else UNARMED * v
        return 0.0


CLAUSES = Automaton()


class Grammar:
    """The lexicon, learned and fixed, over the composed automaton."""

    def __init__(self, words: dict[str, float], stems: dict[str, float]):
        self.words, self.stems = words, stems
        self.fixed = {w: k for k, ws in (("threat", THREATS), ("target", TARGETS), ("negation", NEGATIONS), ("report", REPORTS)) for w in ws}
        self.lengths = sorted({len(s) for s in stems})
        self._seek = None

    def __getstate__(self):
        return self.__dict__ | {"_seek": None}

    def seek(self):
        """Automaton over insults, stems and threats: no clause without one of them can score."""
        if self._seek is None:
            import ahocorasick

            self._seek = ahocorasick.Automaton(ahocorasick.STORE_INTS)
            for w in {*self.words, *self.stems, *THREATS}:
                self._seek.add_word(w, len(w))
            self._seek.make_automaton()
        return self._seek

    def insult(self, word: str) -> float:
        return max([self.words.get(word, 0.0), *(self.stems.get(word[:k], 0.0) for k in self.lengths)])

    def symbol(self, word: str) -> tuple[str, float]:
        """What the lexicon writes for a word, and the word's own weight."""
        kind = self.fixed.get(word)
        if kind == "threat":
            return "insult" if self.insult(word) else "threat", max(self.insult(word), 0.6)
        if kind:
            return kind, 1.0
        w = self.insult(word)
        return ("insult", w) if w else ("other", 1.0)

    def clause(self, words: list[str]) -> float:
        return CLAUSES.weight(map(self.symbol, words))

    def score(self, text: str) -> float:
        low = text.lower()
        miss, done, first = 0.99, -1, 0
        ends = CLAUSE_END.finditer(low)
        end = next(ends, None)
        for at, _ in self._hits(low):
            if at < done:
                continue
            while end and end.end() <= at:
                first, end = end.end(), next(ends, None)
            done = end.start() if end else len(low)
            miss *= 1 - self.clause(WORD.findall(low, first, done))
        return 1 - miss

    def _hits(self, low: str):
        """Start and length of matches that begin a word."""
        for end, size in self.seek().iter(low):
            at = end - size + 1
            if not at or not low[at - 1].isalpha():
                yield at, size


def forms_of(text: str) -> set[str]:
    """Whole words (marked ``=``) and stems of a text."""
    out: set[str] = set()
    for w in set(WORD.findall(text.lower())):
        if len(w) >= 3:
            out.add("=" + w)
            out.update(w[:k] for k in STEM if k < len(w))
    return out


def _counts(rows: DataFrame, only: set[str] | None) -> DataFrame:
    shipped = rows.sparkSession.sparkContext.broadcast(only)

    def run(batches):
        seen: Counter = Counter()
        for b in slices(batches, "text"):
            for t in texts_of(b, "text"):
                f = forms_of(t)
                seen.update(f if shipped.value is None else f & shipped.value)
        keys = list(seen)
        for k in range(0, len(keys), 50_000):
            part = keys[k : k + 50_000]
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.string()), pa.array([seen[x] for x in part], pa.int64())], ["form", "n"])

    return rows.mapInArrow(run, "form string, n long").groupBy("form").agg(F.sum("n").alias("n"))


def learn(docs: DataFrame, labels: DataFrame, max_rows: int = 4_000, id_col: str = "doc_id", text: str = "text", surprise: float = 4.0) -> Grammar:
    """A grammar from at most ``max_rows`` labelled rows of each class that are not held out."""
    free = labels.where(F.col(id_col).isNotNull() & ~held_out(id_col))
    by = F.xxhash64(id_col)
    toxic, clean = (docs.select(id_col, F.col(text).alias("text")).join(F.broadcast(free.where(F.col("toxic") == k).select(id_col).distinct().orderBy(by, id_col).limit(max_rows)), id_col) for k in (1, 0))
    prior = free.agg(F.avg((F.col("toxic") == 1).cast("double"))).first()[0] or 0.0
    # One of each text: copies would make chance words look telling.
    toxic, clean = (d.groupBy(F.md5(F.coalesce("text", F.lit("")).cast("binary"))).agg(F.first("text").alias("text")).select("text").persist() for d in (toxic, clean))
    n1, n0 = toxic.count(), clean.count()
    if not n1 or not n0:
        return Grammar({}, {})
    least = max(2, n1 // 400)
    in_toxic = {r["form"]: r["n"] for r in _counts(toxic, None).where(F.col("n") >= least).collect()}
    in_clean = {r["form"]: r["n"] for r in _counts(clean, set(in_toxic)).collect()}
    good = telling(in_toxic, in_clean, n1, n0, prior, surprise)
    shipped = docs.sparkSession.sparkContext.broadcast(good)

    def held(batches):
        for b in slices(batches, "text"):
            forms = [forms_of(t) for t in texts_of(b, "text")]
            yield pa.RecordBatch.from_arrays([pa.array([sorted(f & shipped.value.keys()) for f in forms], pa.list_(pa.string())), pa.array([sketch(f) for f in forms], pa.list_(pa.int64()))], ["forms", "sketch"])

    rows = [(set(r["forms"]), r["sketch"]) for r in toxic.mapInArrow(held, "forms array<string>, sketch array<long>").collect()]
    toxic.unpersist()
    clean.unpersist()
    return choose(rows, in_clean, n0, prior, surprise)


def sketch(forms: set[str], k: int = 16) -> list[int]:
    """The least hashes of a document's words; near copies share most of them."""
    return sorted(zlib.crc32(f.encode("utf-8", "surrogatepass")) for f in forms if f[0] == "=")[:k]


def families(sketches: list[list[int]], alike: int = 8) -> list[int]:
    """A family number for each sketch: linked through sketches that share ``alike`` values."""
    family = list(range(len(sketches)))

    def top(i: int) -> int:
        while family[i] != i:
            family[i] = family[family[i]]
            i = family[i]
        return i

    by: dict[int, list[int]] = {}
    for i, s in enumerate(sketches):
        met = Counter(top(j) for x in s for j in by.get(x, ()))
        for j, n in met.items():
            if n >= min(alike, len(s)):
                family[top(i)] = top(j)
        for x in s:
            heads = by.setdefault(x, [])
            if all(top(j) != top(i) for j in heads):  # one member of a family stands for it
                heads.append(i)
    return [top(i) for i in range(len(sketches))]


def _surprise(a: int, b: int, share: float) -> float:
    """Large-deviation bound on ``a`` toxic among ``a + b`` by chance, in powers of ten."""
    q = a / (a + b)
    if q <= share:
        return 0.0
    return (a + b) * (q * math.log(q / share) + ((1 - q) * math.log((1 - q) / (1 - share)) if q < 1 else 0.0)) / math.log(10)


def telling(in_toxic: dict[str, int], in_clean: dict[str, int], n1: int, n0: int, prior: float, surprise: float) -> dict[str, float]:
    """Forms that make a document toxic with a chance of 0.8 or more, beyond coincidence."""
    out = {}
    for f, a in in_toxic.items():
        b = in_clean.get(f, 0)
        chance = prior * a / n1 / (prior * a / n1 + (1 - prior) * (b + 0.5) / n0)
        if chance >= 0.8 and _surprise(a, b, n1 / (n1 + n0)) >= surprise:
            out[f] = chance
    return out


def choose(rows: list[tuple[set[str], list[int]]], in_clean: dict[str, int], n0: int, prior: float, surprise: float) -> Grammar:
    """Telling forms, counted once a family of near copies, as words and stems."""
    family = families([s for _, s in rows])
    count = Counter(f for _, f in {(k, f) for k, (forms, _) in zip(family, rows, strict=True) for f in forms})
    n1 = max(1, len(set(family)))
    good = telling(count, in_clean, n1, n0, prior, surprise)
    words, stems, roots = {}, {}, set()
    for f in sorted(good, key=lambda f: (len(f.lstrip("=")), f)):
        word = f.lstrip("=")
        if any(word[:k] in roots for k in range(3, len(word) + 1)):
            continue
        # The longest form that nearly always stands where this one does: a whole word if there is one.
        same = [g for g in good if g.lstrip("=").startswith(word) and count[g] >= 0.9 * count[f]]
        best = max(same, key=lambda g: (len(g.lstrip("=")), g[0] == "=", g))
        roots.add(word)
        (words if best[0] == "=" else stems)[best.lstrip("=")] = min(0.98, good[best])
    return Grammar(words, stems)


def judge(docs: DataFrame, grammar: Grammar, text: str = "text", least: float = 0.3) -> DataFrame:
    """The documents with toxicity (0 to 1) and toxic (1 where it is at least ``least``)."""
    shipped = docs.sparkSession.sparkContext.broadcast(grammar)

    def run(batches):
        for b in slices(batches, text):
            p = [shipped.value.score(t) for t in texts_of(b, text)]
            yield with_columns(b, {"toxicity": pa.array(p, pa.float64()), "toxic": pa.array([int(x >= least) for x in p], pa.int32())})

    kept = [f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields if f.name not in ("toxicity", "toxic")]
    return docs.mapInArrow(run, ", ".join([*kept, "toxicity double", "toxic int"]))
