"""Byte-level BPE with cached words, over public rank files given by path."""

from __future__ import annotations

import base64
import functools
import re

import numpy as np

#: Numeric characters below U+0250 that are not decimal digits.
_OTHER_NUMERIC = "²³¹¼½¾"
#: Characters on which Python's classes and Unicode's agree once the above are set apart.
_PLAIN = re.compile(r"[\x00-\x1b\x20-ɏ]*\Z")
_FAST = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?[^\W\d_{_OTHER_NUMERIC}]+| ?[\d{_OTHER_NUMERIC}]+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+")


def vocabulary_path(name: str) -> str:
    """Place of a public vocabulary file on this machine (driver or executor)."""
    import public_tokenizers

    return public_tokenizers.path(name)


@functools.cache
def _slow():
    import public_tokenizers
    import regex

    return regex.compile(public_tokenizers.PATTERN)


def is_plain(text: str) -> bool:
    return text.isascii() and not re.search("[\x1c-\x1f]", text) or _PLAIN.match(text) is not None


def pattern_for(text: str):
    """A compiled pattern that splits ``text`` as the published one does."""
    return _FAST if is_plain(text) else _slow()


def split(text: str) -> list[str]:
    return pattern_for(text).findall(text)


@functools.cache
def ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


@functools.cache
def encoding(path: str):
    """The rank file as a tiktoken encoding without special tokens."""
    import public_tokenizers
    import tiktoken

    return tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks(path), special_tokens={})


@functools.cache
def token_bytes(path: str) -> list[bytes]:
    """Token-byte table by id; its size is the vocabulary's."""
    table = ranks(path)
    out = [b""] * (max(table.values()) + 1)
    for k, v in table.items():
        out[v] = k
    return out


class WordCache(dict):
    """word -> value by ``make``; forgets all at ``limit`` words, which bounds memory."""

    def __init__(self, make, limit: int = 400_000):
        self.make, self.limit = make, limit

    def __missing__(self, word):
        if len(self) >= self.limit:
            self.clear()
        value = self[word] = self.make(word)
        return value


def ragged(flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Concatenate flat[s:s+n] for each (s, n) without a Python loop."""
    total = int(lengths.sum())
    if not total:
        return flat[:0]
    ends = np.cumsum(lengths)
    return flat[np.arange(total) + np.repeat(starts - (ends - lengths), lengths)]
