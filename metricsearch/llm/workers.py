"""What Python workers keep between tasks: tables of one operator at a time.

Spark reuses workers, so what one operator keeps to go faster would add to the memory of the next.
"""

from __future__ import annotations

import ctypes
import gc
import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_kept: dict[str, Callable[[], None]] = {}
_last: str | None = None  # the operator whose task ran here before
_given_back = 0.0  # when free memory last went back to the system


def keeps(name: str, drop: Callable[[], None]) -> None:
    """Remember how to drop what the operator ``name`` keeps in this worker."""
    _kept[name] = drop


def begin(name: str) -> None:
    """A task of the operator ``name`` begins or goes on: what others keep goes, and free memory goes back to the
    system, once a second at most where the operator is the same."""
    global _last, _given_back
    now = time.monotonic()
    if _last in (None, name):
        _last = name
        if now < _given_back + 1:
            return
    else:
        _last = name
        for x in [x for x in _kept if x != name]:
            _kept.pop(x)()
        gc.collect()
    _given_back = now
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        return


def slices(batches: Iterator[pa.RecordBatch], rows: int = 1000, size: int = 2 << 20, name: str = "text") -> Iterator[pa.RecordBatch]:
    """The batches in slices of at most ``rows`` rows and about ``size`` bytes of the column ``name`` (one row at least),
    so that what is made of one stays small."""
    for batch in batches:
        upto = np.cumsum(pc.fill_null(pc.binary_length(batch[name]), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
        first = 0
        while first < batch.num_rows:
            before = int(upto[first - 1]) if first else 0
            end = min(first + rows, batch.num_rows, max(first + 1, int(np.searchsorted(upto, before + size, "right"))))
            yield batch.slice(first, end - first)
            first = end
