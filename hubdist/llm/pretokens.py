"""Splitting text into the pieces that byte-pair merges never cross, for a whole batch at once."""

from __future__ import annotations

import unicodedata
from functools import cache

import numpy as np

SPACE, LETTER, NUMBER, OTHER = 0, 1, 2, 3
#: Code points with the white-space property.
WHITE = [*range(9, 14), 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]


@cache
def classes() -> np.ndarray:
    """Class of every code point."""
    out = np.full(0x110000, OTHER, np.uint8)
    for c in range(0x110000):
        k = unicodedata.category(chr(c))[0]
        if k == "L":
            out[c] = LETTER
        elif k == "N":
            out[c] = NUMBER
    out[WHITE] = SPACE
    return out


def piece_starts(cp: np.ndarray, off: np.ndarray, keep_space: bool) -> np.ndarray:
    """True where a piece starts; ``off`` bounds the texts.

    ``keep_space``: a single space leads the piece after it, white space stays
    and digits run together; otherwise each white-space run is one piece (to be
    dropped) and every digit stands alone. English contractions are pieces.
    """
    n = len(cp)
    kind = classes()[cp]
    first = np.zeros(n + 1, bool)
    first[off] = True
    first = first[:n]
    start = np.empty(n, bool)
    if not n:
        return start
    start[0] = True
    start[1:] = kind[1:] != kind[:-1]
    if not keep_space:
        start |= kind == NUMBER
    start |= first
    if keep_space:
        white = kind == SPACE
        after = np.zeros(n, bool)  # white space right before something else in the same text
        after[:-1] = white[:-1] & ~white[1:] & ~first[1:]
        start |= after
        led = np.flatnonzero(after & (cp == 32)) + 1
        start[led] = False
    quote = np.flatnonzero((cp == 39) & start)
    if len(quote):
        ends = np.searchsorted(off, quote, "right")
        end = off[ends]
        q1, q2 = np.minimum(quote + 1, n - 1), np.minimum(quote + 2, n - 1)
        a, b = np.where(quote + 1 < end, cp[q1], 0), np.where(quote + 2 < end, cp[q2], 0)
        one = np.isin(a, [ord(x) for x in "stmd"])
        two = ((a == ord("r")) & (b == ord("e"))) | ((a == ord("v")) & (b == ord("e"))) | ((a == ord("l")) & (b == ord("l")))
        for found, k in ((quote[one], 2), (quote[two], 3)):
            start[found + 1] = False
            cut = found + k
            start[cut[cut < n]] = True
    return start
