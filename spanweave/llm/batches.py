"""Arrow batches cut into slices of bounded text, so that numpy temporaries stay small whatever the texts."""

from __future__ import annotations

import ctypes
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc


def give_back() -> None:
    """Freed memory goes back to the system: a worker lives on after its task and would keep it."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def slices(batches: Iterable[pa.RecordBatch], column: str = "text", limit: int = 4_000_000) -> Iterator[pa.RecordBatch]:
    """Slices whose texts hold at most ``limit`` bytes together; a longer text stands alone."""
    for batch in batches:
        if not batch.num_rows:
            continue
        size = np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0), dtype=np.int64)
        ends, start = np.cumsum(size), 0
        while start < batch.num_rows:
            before = ends[start - 1] if start else 0
            stop = max(start + 1, int(np.searchsorted(ends, before + limit, side="right")))
            yield batch.slice(start, stop - start)
            start = stop
        give_back()


def codepoints(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)


def bounded_sample(df, rows: int, *keys: str):
    """All rows where there are at most ``rows``, else about ``rows`` of them, those whose keys hash lowest; the same rows on every run."""
    from pyspark.sql import functions as F

    n = df.count()
    if n <= rows:
        return df
    return df.filter(F.xxhash64(*keys) < int(2**64 * (rows / n)) - 2**63)
