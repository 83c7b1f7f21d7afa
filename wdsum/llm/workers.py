"""What a Python worker holds between tasks.

Spark gives a worker one task after the other, of whatever stage and query, as
long as tasks come. Memory that a kernel leaves behind, its caches as well as
pages that the allocators have free, would add up there over all kernels that
have run, beside a JVM that never shrinks by itself.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import pyarrow as pa

#: what kernels keep for later tasks of their kind; those of other kinds drop it
kept: dict[str, object] = {}

_trim = getattr(ctypes.CDLL(None), "malloc_trim", None)


def release() -> None:
    """Gives free pages of Arrow's pool and of the C library's heap back to the system."""
    pa.default_memory_pool().release_unused()
    if _trim:
        _trim(0)


def kernel(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], keeps: bool = False) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``run`` as a task's function: free memory goes back at its end, and before it, unless it ``keeps`` them, all that is ``kept``."""

    def held(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if kept and not keeps:
            kept.clear()
            gc.collect()
            release()
        try:
            yield from run(batches)
        finally:
            release()

    return held
