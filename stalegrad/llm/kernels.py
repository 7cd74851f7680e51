"""NumPy kernels over blocks of whole texts.

Everything here works on Arrow string columns without making a Python object
per word: a block is a run of rows whose UTF-8 bytes lie side by side in one
buffer.  A single text longer than the block limit forms a block of its own,
so memory follows the longest text, not the batch.

Words are maximal runs of bytes other than 0x20 and 0x09-0x0D.  Hashes are
64-bit polynomial fingerprints finished with a bijective mixer; ``WIDE`` users
combine two of them into 128 bits.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa

BLOCK_BYTES = (1 << 18) - 1  # a worker keeps what its largest arrays took, so blocks are small
U64 = np.uint64

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True

LOWER = np.arange(256, dtype=np.uint8)
LOWER[ord("A") : ord("Z") + 1] += 32


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser (xor-shift and multiply)."""
    x = x ^ (x >> U64(32))
    x = x * U64(0xD6E8FEB86659FD93)
    x ^= x >> U64(32)
    x *= U64(0xD6E8FEB86659FD93)
    x ^= x >> U64(32)
    return x


@lru_cache(maxsize=4)
def byte_codes(lane: int) -> np.ndarray:
    """A fixed random 64-bit code for each byte value; lanes are independent."""
    return np.random.default_rng(7_001 + lane).integers(1, 2**63, 256, dtype=np.uint64) * U64(2) + U64(1)


_BASE = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)
_POWERS: dict[tuple[int, bool], np.ndarray] = {}


def powers(n: int, lane: int = 0, inverse: bool = False) -> np.ndarray:
    """``base**i`` modulo 2**64 for i < n (or of the inverse of the base)."""
    have = _POWERS.get((lane, inverse))
    if have is None or len(have) < n:
        size = max(1 << 16, 1 << (n - 1).bit_length())
        base = _BASE[lane] if not inverse else pow(_BASE[lane], -1, 1 << 64)
        out = np.ones(size, dtype=np.uint64)
        out[1] = base
        done = 2
        while done < size:  # double what is known
            step = min(done, size - done)
            out[done : done + step] = out[:step] * U64(pow(base, done, 1 << 64))
            done += step
        have = out
        if size <= 1 << 19:  # more than a block needs is for one long text only
            _POWERS[(lane, inverse)] = have
    return have[:n]


def ranges_hash(codes: np.ndarray, lo: np.ndarray, hi: np.ndarray, lane: int = 0) -> np.ndarray:
    """Fingerprint of each slice codes[lo:hi], equal for equal slices wherever they stand."""
    n = len(codes)
    sums = np.empty(n + 1, dtype=np.uint64)
    sums[0] = 0
    np.cumsum(codes * powers(n, lane), out=sums[1:])
    return mix((sums[hi] - sums[lo]) * powers(n + 1, lane, True)[lo] + (hi - lo).astype(np.uint64))


def windows_hash(codes: np.ndarray, length: int, lane: int = 0) -> np.ndarray:
    """Fingerprints of all slices of one length."""
    n = len(codes)
    if n < length:
        return np.zeros(0, dtype=np.uint64)
    sums = np.empty(n + 1, dtype=np.uint64)
    sums[0] = 0
    np.cumsum(codes * powers(n, lane), out=sums[1:])
    return mix((sums[length:] - sums[:-length]) * powers(n - length + 1, lane, True))


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each run of ``width`` neighbours, by doubling."""
    if len(x) < width:
        return x[:0]
    have = 1
    while have * 2 <= width:
        x = np.minimum(x[: len(x) - have], x[have:])
        have *= 2
    rest = width - have
    return np.minimum(x[: len(x) - rest], x[rest:]) if rest else x


def blocks(column: pa.Array, limit: int = BLOCK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets) for consecutive rows; null texts are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null(b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    n = len(column)
    if not n:
        return
    _, where, data = column.buffers()
    offs = np.frombuffer(where, dtype=np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, dtype=np.uint8)
    row = 0
    while row < n:
        end = max(row + 1, int(np.searchsorted(offs, offs[row] + limit, side="right")) - 1)
        yield row, end, raw[offs[row] : offs[end]], offs[row : end + 1] - offs[row]
        row = end


def word_spans(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and first-word index by row: words of row r are first[r]:first[r+1]."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offs), np.int64)
    solid = ~_SPACE[data]
    begins, ends = solid.copy(), solid.copy()
    begins[1:] &= ~solid[:-1]
    ends[:-1] &= ~solid[1:]
    inner = offs[1:-1]
    inner = inner[(inner > 0) & (inner < len(data))]
    begins[inner] = solid[inner]
    ends[inner - 1] = solid[inner - 1]
    start = np.flatnonzero(begins)
    return start, np.flatnonzero(ends) + 1, np.searchsorted(start, offs)


def word_codes(data: np.ndarray, start: np.ndarray, end: np.ndarray, lane: int = 0) -> np.ndarray:
    return ranges_hash(byte_codes(lane)[data], start, end, lane)
