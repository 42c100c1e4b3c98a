"""Vectorised scans over Arrow text columns: bytes, words, 64-bit content hashes.

Every scan works on a flat byte buffer with document offsets, so a batch of documents costs a
fixed number of numpy passes. Hashes are polynomials modulo the prime 2^61 - 1 (a power of two as
the modulus lets parity words of 1024 letters collide at any base); where a hash decides a result,
a second base gives another one, independent of the first. ``pieces`` bounds how many bytes are held at a time (one document
is never cut; a longer one makes a piece of its own).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

PIECE_BYTES = 1 << 20
U64 = np.uint64


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on uint64."""
    x = x.astype(U64, copy=True)
    x ^= x >> U64(30)
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


PRIME = (1 << 61) - 1
_P, _LOW31, _LOW30 = U64(PRIME), U64((1 << 31) - 1), U64((1 << 30) - 1)

#: Bases of the two content hashes, random numbers below PRIME.
BASES = (0x0E5F8A3C91D2B647, 0x17C4D06B3EA98F51)


def _fold(x: np.ndarray) -> np.ndarray:
    """Any uint64 to its residue; in place."""
    high = x >> U64(61)
    x &= _P
    x += high
    np.subtract(x, _P, out=x, where=x >= _P)
    return x


STEP = 1 << 14  # entries at a time, so that what a product needs stays in cache


def mul_mod(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """x * y modulo PRIME, for residues."""
    if len(x) <= STEP:
        return _product(x, y)
    out = np.empty(len(x), U64)
    for lo in range(0, len(x), STEP):
        out[lo : lo + STEP] = _product(x[lo : lo + STEP], y if y.ndim == 0 else y[lo : lo + STEP])
    return out


def _product(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Limbs of 31 bits keep every term within 64."""
    x0, x1, y0, y1 = x & _LOW31, x >> U64(31), y & _LOW31, y >> U64(31)
    mid = x1 * y0
    mid += x0 * y1
    x1 *= y1
    x1 <<= U64(1)
    x0 *= y0
    x1 += x0
    x1 += mid >> U64(30)
    mid &= _LOW30
    mid <<= U64(31)
    x1 += mid
    return _fold(x1)


_BYTE_CODE = _fold(mix64(np.arange(1, 257, dtype=U64) * U64(0x9E3779B97F4A7C15)))
_powers: dict[tuple[int, bool], np.ndarray] = {}


def _power(n: int, which: int, inverse: bool = False) -> np.ndarray:
    """base**0 .. base**(n-1) modulo PRIME, or of the inverse; grown by doubling and kept."""
    have = _powers.get((which, inverse))
    if have is None or len(have) < n:
        base = pow(BASES[which], -1, PRIME) if inverse else BASES[which]
        have = np.ones(1, U64) if have is None else have
        most = max(n, PIECE_BYTES + 1)
        while len(have) < most:
            step = np.array(pow(base, len(have), PRIME), U64)
            have = np.concatenate([have, mul_mod(have[: most - len(have)], step)])
        if n <= 8 * PIECE_BYTES:
            _powers[which, inverse] = have
    return have[:n]


def prefix_sums(codes: np.ndarray, which: int = 0) -> np.ndarray:
    """Prefix sums modulo PRIME whose differences give position-free hashes of any span."""
    out = np.zeros(len(codes) + 1, dtype=U64)
    power, two31 = _power(len(codes), which), np.array(1 << 31, U64)
    for lo in range(0, len(codes), STEP):  # sums of limbs cannot overflow within a step
        hi = min(lo + STEP, len(codes))
        terms = _product(_fold(codes[lo:hi].astype(U64, copy=True)), power[lo:hi])
        total = _product(np.cumsum(terms >> U64(31)), two31)
        total += np.cumsum(terms & _LOW31)
        total += out[lo]
        out[lo + 1 : hi + 1] = _fold(total)
    return out


def span_hash(sums: np.ndarray, start: np.ndarray, end: np.ndarray, which: int = 0) -> np.ndarray:
    """64-bit hash of the codes in [start, end) for every pair, length included."""
    power = _power(len(sums), which, True)
    out = np.empty(len(start), U64)
    for lo in range(0, len(start), STEP):
        a, b = start[lo : lo + STEP], end[lo : lo + STEP]
        raw = sums[b]
        raw += _P - sums[a]
        raw = _product(_fold(raw), power[a])
        raw += (b - a).astype(U64) * U64(0x9E3779B97F4A7C15)
        out[lo : lo + STEP] = mix64(raw)
    return out


def byte_codes(buf: np.ndarray) -> np.ndarray:
    return _BYTE_CODE[buf]


#: The six ASCII white-space bytes that separate words.
WORD_SPACE = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)
_SPACE = np.zeros(256, dtype=bool)
_SPACE[list(WORD_SPACE)] = True


def word_spans(buf: np.ndarray, off: np.ndarray, space: np.ndarray = _SPACE):
    """(start, end, document) of every maximal run of non-space bytes within one document."""
    if not len(buf):
        z = np.zeros(0, dtype=np.int64)
        return z, z, z
    ink = ~space[buf]
    first = np.zeros(len(buf) + 1, dtype=bool)
    first[off] = True
    start = ink.copy()
    start[1:] &= ~ink[:-1] | first[1:-1]
    end = ink.copy()
    end[:-1] &= ~ink[1:] | first[1:-1]
    s, e = np.flatnonzero(start), np.flatnonzero(end) + 1
    return s, e, np.searchsorted(off, s, "right") - 1


def as_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Flat bytes and offsets (from 0) of a text or binary column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary())
    if column.null_count:
        column = pc.fill_null(column, b"")
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offs, data = column.buffers()
    off = np.frombuffer(offs, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    buf = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return buf[off[0] : off[-1]], off - off[0]


def pieces(buf: np.ndarray, off: np.ndarray, limit: int = PIECE_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of documents of at most ``limit`` bytes, or of one longer document."""
    i, n = 0, len(off) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(off, off[i] + limit, "right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


def text_hash(buf: np.ndarray, off: np.ndarray) -> np.ndarray:
    """64-bit content hash of every document."""
    return span_hash(prefix_sums(byte_codes(buf)), off[:-1], off[1:])


def group_bounds(*keys: np.ndarray) -> np.ndarray:
    """Starts of the runs of equal keys in sorted columns, with the total at the end."""
    n = len(keys[0])
    if not n:
        return np.zeros(1, dtype=np.int64)
    new = np.zeros(n, dtype=bool)
    new[0] = True
    for k in keys:
        new[1:] |= k[1:] != k[:-1]
    return np.append(np.flatnonzero(new), n)


def ranges(start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """start[0]..start[0]+count[0]-1, start[1].., as one array."""
    total = int(count.sum())
    if not total:
        return np.zeros(0, dtype=np.int64)
    begin = np.cumsum(count) - count
    return np.repeat(start - begin, count) + np.arange(total)
