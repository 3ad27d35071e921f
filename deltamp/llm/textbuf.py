"""Arrow string columns as flat numpy buffers, so that text kernels run without a loop over characters."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa

#: Bytes of text that a kernel handles at once; one longer text forms a group by itself.
GROUP_BYTES = 1 << 18

U64 = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1


def utf8(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes, n + 1 offsets into them and validity of a string column; a null has no bytes."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    kind = np.int64 if pa.types.is_large_string(column.type) else np.int32
    n = len(column)
    valid = np.asarray(column.is_valid()) if column.null_count else np.ones(n, bool)
    _, offsets, data = column.buffers()
    if not n or data is None:
        return np.empty(0, np.uint8), np.zeros(n + 1, np.int64), valid
    at = np.frombuffer(offsets, kind, n + 1, column.offset * np.dtype(kind).itemsize).astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[at[0] : at[-1]]
    at = at - at[0]
    if column.null_count and (at[1:][~valid] > at[:-1][~valid]).any():  # bytes below a null are not text
        keep = np.repeat(valid, np.diff(at))
        raw, at = raw[keep], np.concatenate(([0], np.cumsum(np.where(valid, np.diff(at), 0))))
    return raw, at, valid


def groups(offsets: np.ndarray, limit: int = GROUP_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of rows of at most ``limit`` bytes each, or one row."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1)
        yield i, j
        i = j


def codepoints(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Code points of whole UTF-8 texts, and the offsets counted in code points."""
    starts = np.concatenate(([0], np.cumsum((raw & 0xC0) != 0x80)))
    text = raw.tobytes().decode("utf-8", "surrogatepass")
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32), starts[offsets]


@lru_cache(maxsize=4)
def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the hash base and of its inverse modulo 2**64."""
    inverse = pow(_BASE, -1, 1 << 64)
    with np.errstate(over="ignore"):
        up, down = np.full(n, _BASE, U64), np.full(n, inverse, U64)
        up[0] = down[0] = 1
        return np.cumprod(up), np.cumprod(down)


@lru_cache(maxsize=2)
def letters(n: int, seed: int = 12345) -> np.ndarray:
    return np.random.default_rng(seed).integers(1, 1 << 63, n, dtype=np.int64).astype(U64) | U64(1)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit."""
    h = h.copy()
    h ^= h >> U64(33)
    h *= U64(0xFF51AFD7ED558CCD)
    h ^= h >> U64(33)
    h *= U64(0xC4CEB9FE1A85EC53)
    h ^= h >> U64(33)
    return h


def span_hashes(symbols: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span of 64-bit symbols; the same span has the same hash anywhere."""
    n = 1 << max(16, int(len(symbols)).bit_length())
    up, down = powers(n)
    total = np.zeros(len(symbols) + 1, U64)
    np.cumsum(symbols * up[: len(symbols)], out=total[1:])
    h = (total[ends] - total[starts]) * down[starts]
    return mix(h ^ (ends - starts).astype(U64) * U64(0xD6E8FEB86659FD93))


def runs(inside: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the runs of ``inside``, none across an offset, and the number before each offset."""
    n = len(inside)
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    start = inside.copy()
    start[1:] &= ~inside[:-1] | edge[1:n]
    stop = inside.copy()
    stop[:-1] &= ~inside[1:] | edge[1:n]
    starts = np.flatnonzero(start)
    return starts, np.flatnonzero(stop) + 1, np.searchsorted(starts, offsets)
