"""Vectorised text primitives: whole Arrow batches as one array, never a row at a time.

A string span is hashed by a prefix sum of mixed characters times powers of an
odd number modulo 2**64, so that the hash of any span costs one subtraction and
one product. Long spans can be made that collide under it, so it serves spans of a
few characters or of a few hashed words; whole words are told apart by their bytes
or by a hash that mixes in turn. All hashes are pure functions of the text: they agree
between tasks, retries and machines.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
_POW: dict[int, tuple[np.ndarray, np.ndarray]] = {}
BASES = (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93)


def fmix(x: np.ndarray) -> np.ndarray:
    """A finaliser of 64 bits that spreads every bit."""
    x = x ^ (x >> U(33))
    x *= U(0xFF51AFD7ED558CCD)
    x ^= x >> U(33)
    x *= U(0xC4CEB9FE1A85EC53)
    x ^= x >> U(33)
    return x


def powers(n: int, which: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Powers 0..n of the base and of its inverse modulo 2**64."""
    held = _POW.get(which)
    if held is None or len(held[0]) <= n:
        r = BASES[which]
        size = 1 << max(16, int(n).bit_length())
        out = []
        for x in (r, pow(r, -1, 1 << 64)):
            a = np.full(size, U(x))
            a[0] = U(1)
            out.append(np.multiply.accumulate(a))
        _POW[which] = held = (out[0], out[1])
    return held


def prefix(chars: np.ndarray, which: int = 0) -> np.ndarray:
    """Prefix sums for ``span_hash`` over an array of character codes."""
    v = chars.astype(U)
    v += U(0x632BE59BD9B4E019 if which else 0x2545F4914F6CDD1D)
    v *= U(0xA0761D6478BD642F)
    v ^= v >> U(32)
    v *= U(0xE7037ED1A0B428DB)
    v *= powers(len(chars), which)[0][: len(chars)]
    out = np.empty(len(chars) + 1, U)
    out[0] = U(0)
    np.cumsum(v, out=out[1:])
    return out


def span_hash(p: np.ndarray, start: np.ndarray, end: np.ndarray, which: int = 0) -> np.ndarray:
    """Hash of each span [start, end); equal texts have equal hashes wherever they stand."""
    h = p[end] - p[start]
    h *= powers(len(p), which)[1][start]
    h += (end - start).astype(U) * U(0x9FB21C651E98DF25)
    return fmix(h)


def texts(col: pa.Array | pa.ChunkedArray) -> list[str]:
    """Strings of a column, null as the empty text."""
    return [x or "" for x in col.to_pylist()]


def utf8(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column and the offsets of its rows; null is empty. No copy."""
    if pa.types.is_large_string(col.type):
        kind = np.int64
    else:
        col, kind = col.cast(pa.string()), np.int32
    if col.null_count:
        col = col.fill_null("")
    _, off, data = col.buffers()
    o = np.frombuffer(off, kind)[col.offset : col.offset + len(col) + 1].astype(np.int64) if len(col) else np.zeros(1, np.int64)
    b = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return b[o[0] : o[-1]], o - o[0]


def slices(sizes: np.ndarray, limit: int) -> Iterator[tuple[int, int]]:
    """Runs of rows with at most ``limit`` units of text each; a longer row stands alone."""
    i, n = 0, len(sizes)
    total = np.concatenate([[0], np.cumsum(sizes)])
    while i < n:
        j = max(i + 1, int(np.searchsorted(total, total[i] + limit, "right")) - 1)
        yield i, min(j, n)
        i = j


def code_points(rows: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all rows in one array, with the offsets of the rows."""
    off = np.concatenate([[0], np.cumsum(np.fromiter(map(len, rows), np.int64, len(rows)))])
    return np.frombuffer("".join(rows).encode("utf-32-le", "surrogatepass"), np.uint32), off


def column_points(col: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """``code_points`` of a string column, without a Python string for each row."""
    data, off = utf8(col.combine_chunks() if isinstance(col, pa.ChunkedArray) else col)
    if not (data & 0x80).any():
        return data.astype(np.uint32), off
    at = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
    return np.frombuffer(data.tobytes().decode("utf-8", "surrogatepass").encode("utf-32-le", "surrogatepass"), np.uint32), at[off]


def piece_batches(batches: Iterator[pa.RecordBatch], limit: int = 1 << 20, at: int = 1) -> Iterator[pa.RecordBatch]:
    """Arrow batches cut into runs of rows with bounded text in column ``at``."""
    for batch in batches:
        lens = np.asarray(pc.fill_null(pc.binary_length(batch.column(at)), 0).to_numpy(zero_copy_only=False), np.int64)
        for i, j in slices(lens, limit):
            yield batch.slice(i, j - i)


def text_batches(batches: Iterator[pa.RecordBatch], limit: int = 1 << 20) -> Iterator[tuple[list, list[str], pa.RecordBatch]]:
    """Rows of Arrow batches (id column first, then text) in pieces of bounded text."""
    for piece in piece_batches(batches, limit):
        yield piece.column(0).to_pylist(), texts(piece.column(1)), piece


def words_of(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> pa.Array:
    """Spans [start, end) of a byte array, which do not overlap and come in order, as a binary array."""
    n = (end - start).astype(np.int64)
    off = np.concatenate([[0], np.cumsum(n)])
    edge = np.zeros(len(data) + 1, np.int8)
    edge[start] += 1
    np.subtract.at(edge, end, 1)  # an end may be the next start
    held = data[np.cumsum(edge[:-1], dtype=np.int8) > 0] if len(data) else data
    return pa.Array.from_buffers(pa.large_binary(), len(n), [None, pa.py_buffer(off), pa.py_buffer(np.ascontiguousarray(held))])


def same_words(words: pa.Array) -> tuple[np.ndarray, pa.Array]:
    """For each span a code that equal bytes share, and the span of each code: compared byte by byte, not by a hash."""
    held = words.dictionary_encode()
    return held.indices.to_numpy(zero_copy_only=False).astype(np.int64), held.dictionary


_ENDS = np.array([(1 << 8 * k) - 1 for k in range(9)], U)


def word_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hash of each span [start, end) of a byte array: eight bytes at a time go through two mixing states of 64 bits, so no sum of powers is left to collide."""
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    eight = np.ndarray((len(data) + 1,), "<u8", padded, strides=(1,))
    size = (end - start).astype(np.int64)
    h, g = size.astype(U) + U(0x9E3779B97F4A7C15), np.full(len(size), U(0xD6E8FEB86659FD93))
    live, at = np.arange(len(size)), 0
    while len(live):
        left = size[live] - at
        lane = eight[start[live] + at] & _ENDS[np.minimum(left, 8)]
        x = fmix(h[live] ^ lane)
        y = (g[live] + lane) * U(0xA0761D6478BD642F)
        y = (y ^ (y >> U(29))) + ((x << U(23)) | (x >> U(41)))
        h[live], g[live] = x, y
        at += 8
        live = live[left > 8]
    return fmix(h ^ fmix(g))


def utf8_places(cp: np.ndarray) -> np.ndarray:
    """Place of each code point, and of the end, in the UTF-8 form of the same text."""
    size = (cp >= 0x80).astype(np.int8)
    size += cp >= 0x800
    size += cp >= 0x10000
    size += 1
    out = np.zeros(len(cp) + 1, np.int64)
    np.cumsum(size, out=out[1:])
    return out


def spans_of(starts: np.ndarray, n: int, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Row of each span start, and how many spans each row has."""
    row = np.searchsorted(off, starts, "right") - 1
    return row, np.bincount(row, minlength=n)


