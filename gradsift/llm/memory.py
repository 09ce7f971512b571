"""Free memory of Python workers, which outlive their tasks, goes back to the system."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa

Batches = Iterator[pa.RecordBatch]


def trim() -> None:
    """Returns what the allocators keep for later use. Where the C library has no such call, only Arrow's."""
    pa.default_memory_pool().release_unused()
    give = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if give is not None:
        give(0)


def trimmed(run: Callable[[Batches], Batches]) -> Callable[[Batches], Batches]:
    """The function over batches, with a trim after a task's last one."""

    def whole(batches: Batches) -> Batches:
        yield from run(batches)
        trim()

    return whole
