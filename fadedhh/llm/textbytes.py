"""Vectorised kernels over the UTF-8 bytes of an Arrow string column.

Words are runs of bytes outside a separator set, so byte-level scanning equals the character-level
definition: every separator is ASCII and UTF-8 continuation bytes never are.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

_MASK = np.uint64(0xFFFFFFFFFFFFFFFF)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _stream(seed: int, n: int) -> np.ndarray:
    return mix64(np.arange(1, n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed))


BYTE_CODE = _stream(11, 256)
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Separators of the space-delimited words: space and the control characters tab to carriage return.
SPACED = np.ones(256, bool)
SPACED[[0x20, *range(0x09, 0x0E)]] = False
#: Alphanumeric words: ASCII digits, letters and everything beyond ASCII.
ALNUM = np.zeros(256, bool)
ALNUM[0x30:0x3A] = ALNUM[0x61:0x7B] = ALNUM[0x41:0x5B] = True
ALNUM[0x80:] = True

_BASE = np.uint64(0x9E3779B97F4A7C15)
_powers = np.ones(1, np.uint64)


def powers(n: int) -> np.ndarray:
    """The first n powers of an odd multiplier modulo 2**64."""
    global _powers
    if len(_powers) < n:
        size = max(n, 2 * len(_powers), 4096)
        p = np.full(size, _BASE)
        p[0] = 1
        _powers = np.multiply.accumulate(p)
    return _powers[:n]


def raw(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string array without copying; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if not pa.types.is_binary(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, at, data = column.buffers()
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(at, np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    whole = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return whole[offsets[0] : offsets[-1]], offsets - offsets[0]


def runs_of_rows(offsets: np.ndarray, budget: int, most: int = 1 << 30):
    """Ranges of at most ``most`` rows whose bytes stay near ``budget``; a longer row stands alone."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = int(np.searchsorted(offsets, offsets[i] + budget, side="right")) - 1
        j = min(n, i + most, max(i + 1, j))
        yield i, j
        i = j


#: Codes of bytes by separator set, 0 for separators, and the powers of the inverse multiplier.
_codes: dict[bytes, np.ndarray] = {}
_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_inverses = np.ones(1, np.uint64)
#: Bytes that are hashed by powers of their place in the data; more go by their place in the word.
NEAR = 1 << 22


def _unpowers(n: int) -> np.ndarray:
    """The first n powers of the multiplier's inverse modulo 2**64."""
    global _inverses
    if len(_inverses) < n:
        p = np.full(max(n, 2 * len(_inverses), 4096), _INVERSE)
        p[0] = 1
        _inverses = np.multiply.accumulate(p)
    return _inverses[:n]


def words(data: np.ndarray, offsets: np.ndarray, keep: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(64-bit hashes of lower-cased words in text order, number of words of each row)."""
    rows = len(offsets) - 1
    if not len(data):
        return np.zeros(0, np.uint64), np.zeros(rows, np.int64)
    inside = keep[data]
    first = np.zeros(len(data) + 1, bool)
    first[offsets] = True
    start = inside.copy()
    start[1:] &= ~inside[:-1] | first[1:-1]
    begin = np.flatnonzero(start)
    count = np.diff(np.searchsorted(begin, offsets))
    if not len(begin):
        return np.zeros(0, np.uint64), count
    if len(data) > NEAR:
        at = np.flatnonzero(inside)
        head = np.searchsorted(at, begin)
        size = np.diff(np.append(head, len(at)))
        within = np.arange(len(at)) - np.repeat(head, size)
        total = np.add.reduceat(BYTE_CODE[LOWER[data[at]]] * powers(int(size.max()))[within], head)
    else:
        inside[:-1] &= ~inside[1:] | first[1:-1]  # the last byte of each word
        size = np.flatnonzero(inside) - begin + 1
        code = _codes.setdefault(keep.tobytes(), np.where(keep, BYTE_CODE[LOWER], np.uint64(0)))
        total = np.add.reduceat(code[data] * powers(len(data)), begin) * _unpowers(len(data))[begin]
    return mix64(total + size.astype(np.uint64)), count
