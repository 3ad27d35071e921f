"""Groups of sorted rows that a Python worker reads as a stream, and what a worker keeps between batches."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa


def whole_groups(batches: Iterator[pa.RecordBatch], limit: int = 4 << 20) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Tables of whole groups (equal first three columns, sorted) with the starts of the groups, of about ``limit`` bytes or one group."""
    held: list[pa.Table] = []

    def starts(t: pa.Table) -> np.ndarray:
        k = np.stack([t.column(c).to_numpy() for c in range(3)])
        return np.concatenate(([0], np.flatnonzero((k[:, 1:] != k[:, :-1]).any(0)) + 1)) if t.num_rows else np.empty(0, int)

    for batch in batches:
        held.append(pa.Table.from_batches([batch]))
        if sum(t.nbytes for t in held) >= limit:
            t = pa.concat_tables(held)
            at = starts(t)
            if len(at) > 1:  # the last group may go on
                yield t.slice(0, at[-1]), at[:-1]
                held = [t.slice(at[-1])]
            else:
                held = [t]
    if held and (t := pa.concat_tables(held)).num_rows:
        yield t, starts(t)


_caches: dict[str, Callable[[], None]] = {}
_owner = ""


def caches(owner: str, clear: Callable[[], None]) -> None:
    """Tells how to empty what an operator keeps in a worker from batch to batch."""
    _caches[owner] = clear


def enter(owner: str) -> None:
    """An operator begins in this worker: what any other one keeps here goes, so a worker never holds the caches of two."""
    global _owner
    if owner == _owner:
        return
    for name, clear in _caches.items():
        if name != owner:
            clear()
    _owner = owner
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library keeps its free memory as it likes
        pass
