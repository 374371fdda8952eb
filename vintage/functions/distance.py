"""Bounded edit distance by bit vectors, for the pairs that cheaper tests leave.

Spark's own ``levenshtein`` fills its table cell by cell and takes a constant
bound. Here a column of the table is one integer of as many bits as the band is
wide, so a step costs a few machine words (the published bit-parallel scheme,
its banded form). Distances count code points.
"""

from __future__ import annotations


def shared_start(a: str, b: str) -> int:
    """Number of characters two texts share at their start, by halving."""
    low, high = 0, min(len(a), len(b))
    if a[:high] == b[:high]:
        return high
    while high - low > 1:
        mid = (low + high) // 2
        if a[low:mid] == b[low:mid]:
            low = mid
        else:
            high = mid
    return low


def stripped(a: str, b: str) -> tuple[str, str]:
    """The texts without a start and an end that they share; their distance stays."""
    n = shared_start(a, b)
    a, b = a[n:], b[n:]
    n = shared_start(a[::-1], b[::-1])
    return (a[:-n], b[:-n]) if n else (a, b)


def _places(text: str) -> dict[str, int]:
    """For each character the bits of the positions it stands at."""
    by: dict[str, list[int]] = {}
    for i, c in enumerate(text):
        by.setdefault(c, []).append(i)
    out = {}
    for c, at in by.items():
        bits = bytearray((at[-1] >> 3) + 1)
        for i in at:
            bits[i >> 3] |= 1 << (i & 7)
        out[c] = int.from_bytes(bits, "little")
    return out


def _whole(a: str, b: str) -> int:
    """Distance with a column of full height: for texts no longer than the band."""
    places, every = _places(a), (1 << len(a)) - 1
    up, down, last, dist = every, 0, 1 << (len(a) - 1), len(a)
    for c in b:
        eq = places.get(c, 0)
        diagonal = ((((eq & up) + up) ^ up) | eq | down) & every
        more, less = down | (every ^ (diagonal | up)), diagonal & up
        if more & last:
            dist += 1
        elif less & last:
            dist -= 1
        more = (more << 1 | 1) & every
        up, down = (less << 1 & every) | (every ^ (diagonal | more)), diagonal & more
    return dist


def _banded(a: str, b: str, most: int) -> int | None:
    """Distance if it is at most ``most``, else None; most < len(a), and lengths differ by no more than it.

    The band moves down one row a column. Its lowest row's value is followed
    along the diagonal to the last row, then along that row.
    """
    width = 2 * most + 1
    every, low = (1 << width) - 1, 1 << (width - 1)
    up, down, dist = ((1 << (most + 1)) - 1) << (width - 1 - most), 0, most
    places, start, turn = _places(a), most + 1 - width, len(a) - most
    give_up = 2 * most + len(b) - len(a)
    for i, c in enumerate(b):
        eq = places.get(c, 0)
        if eq:
            eq = (eq >> start if start >= 0 else eq << -start) & every
        diagonal = ((((eq & up) + up) ^ up) | eq | down) & every
        more, less = down | (every ^ (diagonal | up)), diagonal & up
        if i < turn:
            if not diagonal & low:
                dist += 1
        else:
            low >>= 1
            if more & low:
                dist += 1
            elif less & low:
                dist -= 1
        if dist > give_up:
            return None
        diagonal >>= 1
        up, down = less | (every ^ (diagonal | more)), diagonal & more
        start += 1
    return dist if dist <= most else None


def bounded(a: str, b: str, most: int, first: int = 64) -> int | None:
    """Edit distance of two texts if it is at most ``most``, else None.

    Bands double from ``first`` on, so the time goes with length times distance.
    """
    if a == b:
        return 0 if most >= 0 else None
    if abs(len(a) - len(b)) > most:
        return None
    a, b = stripped(a, b)
    if len(a) > len(b):
        a, b = b, a
    if not a:
        return len(b) if len(b) <= most else None
    band = max(first, len(b) - len(a), 1)
    while True:
        band = min(band, most)
        if band >= len(a):
            dist = _whole(a, b)
            return dist if dist <= most else None
        dist = _banded(a, b, band)
        if dist is not None or band >= most:
            return dist
        band *= 2
