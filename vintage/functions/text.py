"""Text columns: folding, tokens, spans, shingles, bounded near-equality."""

from __future__ import annotations

import unicodedata
from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def _accents() -> tuple[str, str]:
    """Latin letters with marks and the ASCII letter below each; one to one, so lengths stay."""
    pairs = {"ß": "s", "æ": "a", "ø": "o", "Æ": "A", "Ø": "O"}
    for c in map(chr, range(0xC0, 0x180)):
        base = unicodedata.normalize("NFD", c)[0]
        if base.isascii() and base.isalpha():
            pairs[c] = base
    return "".join(pairs), "".join(pairs.values())


ACCENTED, PLAIN = _accents()
SENTENCE_MARK = "\x01"


def fold(text: Column) -> Column:
    """ASCII lower case for Latin text; null stays null."""
    return F.lower(F.translate(text, ACCENTED, PLAIN))


def canonical(text: Column) -> Column:
    """Folded text with white space collapsed: what near-identical pages agree on."""
    return F.trim(F.regexp_replace(fold(text), r"\s+", " "))


def tokens(text: Column) -> Column:
    """Words of the canonical text; an empty array for null or blank text."""
    c = F.coalesce(canonical(text), F.lit(""))
    return F.when(c == "", F.array().cast("array<string>")).otherwise(F.split(c, " "))


def head_tokens(text: Column, n: int) -> Column:
    return F.slice(tokens(text), 1, n)


def sentences(text: Column) -> Column:
    """Split behind . ! or ? followed by white space."""
    return F.split(F.regexp_replace(text, r"([.!?])\s+", f"$1{SENTENCE_MARK}"), SENTENCE_MARK)


def shifted(array: Column, by: int) -> Column:
    """The array moved right by ``by`` places, null in front, its length kept."""
    gap = F.array(*[F.lit(None).cast("string")] * by)
    return F.slice(F.concat(gap, array), F.lit(1), F.size(array))


def runs_of(array: Column, n: int, joined: Callable[[list[Column]], Column]) -> Column:
    """``joined`` of every run of n neighbours, in order; empty below n, null for a null array.

    The array is laid beside itself n times, so the whole takes one walk however
    costly the array is to compute; a slice taken for each place would compute it
    again for each.
    """
    beside = F.arrays_zip(*(F.slice(array, F.lit(k + 1), F.greatest(F.size(array), F.lit(0))).alias(f"w{k}") for k in range(n)))
    whole = F.slice(beside, F.lit(1), F.greatest(F.size(array) - (n - 1), F.lit(0)))
    return F.transform(whole, lambda x: joined([x[f"w{k}"] for k in range(n)]))


def joined_runs(array: Column, n: int, glue: str = " ") -> Column:
    """Every run of n neighbours, joined."""
    return runs_of(array, n, lambda ws: F.concat_ws(glue, *ws))


def shingles(words: Column, n: int) -> Column:
    """Distinct runs of n words joined by blanks; empty below n words."""
    return F.array_distinct(joined_runs(words, n))


def limit_of(length: Column, threshold: float, inclusive: bool = False) -> Column:
    """The largest whole edit distance that is below (or at) threshold * length."""
    cut = F.lit(threshold).cast("decimal(6,4)") * length.cast("decimal(12,0)")
    return (F.floor(cut) if inclusive else F.ceil(cut) - 1).cast("int")


def near(a: Column, b: Column, threshold: float = 0.2, inclusive: bool = False, steps: tuple[int, ...] = (150, 300, 600, 1200, 2400, 4800, 9600)) -> Column:
    """Edit distance of b to a where it is below threshold * length(a), else null.

    A native expression for single pairs. Cheapest tests first: equal texts, then
    the length gap, then the built-in distance. That one takes a constant bound,
    so ``steps`` bounds are laid out and each row uses the least that covers its
    own; the distance itself stands in the expression once. For many versions
    of one text ``mining.compare_versions`` is far cheaper.
    """
    most = limit_of(F.char_length(a), threshold, inclusive)
    gap = F.abs(F.char_length(a) - F.char_length(b))
    d = F.levenshtein(a, b)
    for bound in reversed(steps):
        d = F.when(most <= bound, F.levenshtein(a, b, bound)).otherwise(d)
    fits = F.get(F.filter(F.array(d), lambda x: (x >= 0) & (x <= most)), F.lit(0))
    return F.when(a == b, F.when(most >= 0, F.lit(0))).when(gap <= most, fits)
