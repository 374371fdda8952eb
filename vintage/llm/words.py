"""Vectorised words and five-word windows of whole texts, for many texts at once.

A word is a run of bytes other than ASCII white space (0x20, 0x09-0x0D). Words
are hashed without a Python loop: with prefix sums S of c(b_i) * B**i modulo
2**64, the hash of bytes s..e is (S[e] - S[s]) * B**-s, mixed with its length.
"""

from __future__ import annotations

import functools

import numpy as np

_U = np.uint64
#: Odd 64-bit multipliers (public constants of well-known mixers) and their use.
BASE = 0x9E3779B97F4A7C15
MIX_1, MIX_2 = 0xBF58476D1CE4E5B9, 0x94D049BB133111EB
WINDOW, SEGMENT = 5, 1 << 20
_PLACE = np.array([pow(BASE, 2 * k + 3, 1 << 64) | 1 for k in range(WINDOW)], dtype=_U)
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(30))) * _U(MIX_1)
    x = (x ^ (x >> _U(27))) * _U(MIX_2)
    return x ^ (x >> _U(31))


_BYTE = mix(np.arange(1, 257, dtype=_U) * _U(BASE))


@functools.lru_cache(maxsize=1)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    inverse = pow(BASE, -1, 1 << 64)
    up, down = (np.full(n, x, dtype=_U) for x in (BASE, inverse))
    up[0] = down[0] = 1
    return np.cumprod(up), np.cumprod(down)


def word_hashes(buf: np.ndarray, lower: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, start and end of every word of a byte buffer; works in pieces of SEGMENT bytes, cut at white space."""
    parts, at = [], 0
    while at < len(buf) or not parts:
        end = min(len(buf), at + SEGMENT)
        while end < len(buf):
            gaps = np.flatnonzero(_SPACE[buf[max(at, end - 4096) : end]])
            if len(gaps):
                end = max(at, end - 4096) + int(gaps[-1]) + 1
                break
            end = min(len(buf), end + 4096)  # a word longer than what is searched; it stays whole
        h, s, e = _segment(buf[at:end], lower)
        parts.append((h, s + at, e + at))
        at = end
    return parts[0] if len(parts) == 1 else tuple(np.concatenate(x) for x in zip(*parts, strict=True))


def _segment(buf: np.ndarray, lower: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    space = np.ones(len(buf) + 2, bool)
    space[1:-1] = _SPACE[buf]
    edge = np.flatnonzero(space[1:] != space[:-1])
    starts, ends = edge[::2], edge[1::2]
    up, down = _powers(max(SEGMENT, 1 << int(len(buf)).bit_length()))
    sums = np.zeros(len(buf) + 1, dtype=_U)
    np.cumsum(_BYTE[_LOWER[buf] if lower else buf] * up[: len(buf)], out=sums[1:])
    h = (sums[ends] - sums[starts]) * down[starts]
    return mix(h + (ends - starts).astype(_U) * _U(MIX_2)), starts, ends


def joined(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """One buffer of all texts, a line feed after each, and where each text starts (one more at the end)."""
    bounds = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) + 1 for t in texts], out=bounds[1:])
    return np.frombuffer(b"\n".join([*texts, b""]), np.uint8), bounds


def windows(hashes: np.ndarray) -> np.ndarray:
    """Hash of every run of five words; empty below five."""
    n = len(hashes) - WINDOW + 1
    if n <= 0:
        return hashes[:0]
    out = hashes[:n] * _PLACE[0]
    for k in range(1, WINDOW):
        out = out + hashes[k : k + n] * _PLACE[k]
    return mix(out)


def shingle_set(hashes: np.ndarray) -> np.ndarray:
    """Sorted distinct five-word shingles; with fewer words the whole sequence; empty without words."""
    if len(hashes) >= WINDOW:
        return np.unique(windows(hashes))
    if not len(hashes):
        return hashes
    whole = np.zeros(1, _U)
    for h in hashes:
        whole = mix(whole * _PLACE[1] + h)
    return mix(whole + _U(len(hashes)))


def shingle_sets(texts: list[bytes]) -> list[np.ndarray]:
    """The shingle set of each text, A-Z lower-cased; a few megabytes of texts at a time."""
    out: list[np.ndarray] = []
    start = size = 0
    for k in range(len(texts) + 1):
        if k == len(texts) or (k > start and size + len(texts[k]) > SEGMENT):
            buf, bounds = joined(texts[start:k])
            hashes, starts, _ = word_hashes(buf, lower=True)
            cut = np.searchsorted(starts, bounds)
            out += [shingle_set(hashes[a:b]) for a, b in zip(cut[:-1], cut[1:], strict=True)]
            start, size = k, 0
        if k < len(texts):
            size += len(texts[k])
    return out
