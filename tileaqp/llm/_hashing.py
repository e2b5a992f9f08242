"""Rolling hashes over whole Arrow batches: every byte or code point is touched by numpy only."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

ODD = np.uint64(0x9E3779B97F4A7C15)
MIX = np.uint64(0xD6E8FEB86659FD93)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64 bits whose low bits depend on all others."""
    h = h ^ (h >> np.uint64(32))
    h = h * MIX
    h ^= h >> np.uint64(29)
    h = h * ODD
    h ^= h >> np.uint64(32)
    return h


def symbol_codes(n: int, seed: int) -> np.ndarray:
    return mix(np.arange(1, n + 1, dtype=np.uint64) * ODD + np.uint64(seed))


def powers(n: int, base: int) -> np.ndarray:
    """base**0 .. base**n modulo 2**64, by doubling."""
    out = np.ones(n + 1, np.uint64)
    done, step = 1, base
    while done <= n:
        more = min(done, n + 1 - done)
        out[done : done + more] = out[:more] * np.uint64(step)
        done, step = done + more, step * step % (1 << 64)
    return out


def prefix_sums(codes: np.ndarray, pw: np.ndarray) -> np.ndarray:
    """S with S[e] - S[s] = sum of codes[i] * base**i over s <= i < e."""
    out = np.zeros(len(codes) + 1, np.uint64)
    np.cumsum(codes * pw[: len(codes)], out=out[1:])
    return out


def span_hash(sums: np.ndarray, inverse: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hash of each [start, end), the same wherever it stands; inverse has the powers of the inverted base."""
    return (sums[end] - sums[start]) * inverse[start]


def inverse_of(base: int) -> int:
    return pow(base, -1, 1 << 64)


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and the n + 1 offsets into them; null counts as empty."""
    column = column.cast(pa.large_string()).fill_null("")
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]
