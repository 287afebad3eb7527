"""Words and hashes of whole Arrow string columns at once, with numpy.

All functions work on the column's own bytes; nothing is decoded. Word hashes come from one
running sum over the bytes, so their cost does not depend on the words' number.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa

U = np.uint64
MASK = (1 << 64) - 1
BASE = 0x9E3779B97F4A7C15 | 1
BASE_INVERSE = pow(BASE, -1, 1 << 64)
#: Texts are handled in runs of about so many bytes; a longer text makes a run of its own.
RUN_BYTES = 1 << 19


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x + U((salt * 0xD1342543DE82EF95 + 0x632BE59BD9B4E019) & MASK)
    x ^= x >> U(30)
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


BYTE_HASH = mix(np.arange(256, dtype=U), 77)
FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32
#: Bytes of words: all but white space; and letters a-z, digits and everything beyond ASCII.
NOT_WHITE = np.ones(256, dtype=bool)
NOT_WHITE[[9, 10, 11, 12, 13, 32]] = False
ALNUM = np.zeros(256, dtype=bool)
ALNUM[48:58] = ALNUM[97:123] = ALNUM[128:] = True


class Kept(dict):
    """A cache that stays in its process: sent to a task, it arrives empty."""

    def __reduce__(self):
        return (Kept, ())


_powers: dict[int, np.ndarray] = Kept()


def powers(base: int, n: int) -> np.ndarray:
    """base ** 0 .. base ** (n - 1) modulo 2 ** 64; kept for the next call."""
    got = _powers.get(base)
    if got is None or len(got) < n:
        size = max(n, RUN_BYTES + 1, 0 if got is None else 2 * len(got))
        got = np.full(size, base & MASK, dtype=U)
        got[0] = 1
        np.cumprod(got, out=got)
        _powers[base] = got
    return got[:n]


def raw(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of a string column and the n + 1 bounds of its texts; null has none."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_null(column.type):
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    if column.null_count:
        column = column.fill_null("" if not pa.types.is_binary(column.type) and not pa.types.is_large_binary(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, at, data = column.buffers()
    if at is None or not len(column):
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    kind = np.int64 if wide else np.int32
    bounds = np.frombuffer(at, dtype=kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    buf = np.frombuffer(data, dtype=np.uint8)[bounds[0] : bounds[-1]] if data is not None else np.zeros(0, np.uint8)
    return buf, bounds - bounds[0]


def runs(bounds: np.ndarray, limit: int = RUN_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about `limit` bytes."""
    a, n = 0, len(bounds) - 1
    while a < n:
        b = max(a + 1, int(np.searchsorted(bounds, bounds[a] + limit, side="right")) - 1)
        yield a, min(b, n)
        a = min(b, n)


class Words(NamedTuple):
    starts: np.ndarray
    ends: np.ndarray
    #: words of text i are first[i] .. first[i + 1]
    first: np.ndarray
    hashes: np.ndarray


def words(buf: np.ndarray, bounds: np.ndarray, kind: np.ndarray, fold: np.ndarray = FOLD) -> Words:
    """Words of texts: maximal runs of bytes of a kind, with A-Z folded for kind and hash unless `fold` says otherwise."""
    n = len(buf)
    if not n:
        none = np.zeros(0, np.int64)
        return Words(none, none, np.zeros(len(bounds), np.int64), np.zeros(0, U))
    folded = fold[buf]
    inside = kind[folded]
    cutoff = np.zeros(n + 1, dtype=bool)
    cutoff[bounds] = True
    begins = inside.copy()
    begins[1:] &= ~inside[:-1] | cutoff[1:n]
    finishes = inside.copy()
    finishes[:-1] &= ~inside[1:] | cutoff[1:n]
    starts, ends = np.flatnonzero(begins), np.flatnonzero(finishes) + 1
    sums = np.zeros(n + 1, dtype=U)
    np.cumsum(BYTE_HASH[folded] * powers(BASE, n), out=sums[1:])
    hashes = (sums[ends] - sums[starts]) * powers(BASE_INVERSE, n)[starts]
    hashes = mix(hashes + (ends - starts).astype(U))
    return Words(starts, ends, np.searchsorted(starts, bounds), hashes)


def windows(hashes: np.ndarray, width: int) -> np.ndarray:
    """Hashes of all windows of `width` words, whatever text they cross."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.zeros(0, U)
    out = np.zeros(n, dtype=U)
    for k in range(width):
        out += hashes[k : k + n] * U(pow(BASE, k + 1, 1 << 64))
    return mix(out, width)


def shingles(w: Words, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of each text, sorted, and their n + 1 bounds; a text of fewer words has one shingle."""
    counts = np.diff(w.first)
    many = np.maximum(counts - width + 1, (counts > 0).astype(np.int64))
    at = np.concatenate(([0], np.cumsum(many)))
    out = np.empty(at[-1], dtype=U)
    everywhere = windows(w.hashes, width)
    long = counts >= width
    # places of all windows of long texts: consecutive starts from each first word
    which = np.repeat(np.flatnonzero(long), many[long])
    offset = np.arange(len(which)) - np.repeat(np.concatenate(([0], np.cumsum(many[long])))[:-1], many[long])
    out[at[which] + offset] = everywhere[w.first[which] + offset]
    for size in range(1, width):
        short = np.flatnonzero(counts == size)
        if len(short):
            out[at[short]] = windows(w.hashes, size)[w.first[short]]
    for i in range(len(counts)):
        out[at[i] : at[i + 1]].sort()
    fresh = np.ones(len(out), dtype=bool)
    fresh[1:] = out[1:] != out[:-1]
    fresh[at[:-1][many > 0]] = True
    return out[fresh], np.concatenate(([0], np.cumsum(fresh)))[at]


def longs(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64) if x.dtype == U else x.astype(np.int64))


def lists(values: np.ndarray, bounds: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), longs(values))
