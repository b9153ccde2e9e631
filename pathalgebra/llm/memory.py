"""Memory of Python workers, which live on from task to task and from stage to stage.

What a task frees stays with the allocators of its worker, and tables that tasks of
one operator leave for its next ones stay as long as the worker.  An executor's
workers then hold what earlier stages needed while a later one works.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import pyarrow as pa

#: Tables that tasks leave for later tasks of the same operator; each can be made anew.
caches: list[dict] = []


def trimmed() -> None:
    """Gives free memory back to the system, where the C library can do so."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def give_back() -> None:
    """Drops other operators' tables as well."""
    for cache in caches:
        cache.clear()
    trimmed()


def lean(work: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], alone: bool = True) -> Callable:
    """The same work of a task; its memory goes back when the task ends.

    ``alone``: the work needs no table of earlier tasks, so those are dropped before it begins.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if alone:
            give_back()
        try:
            yield from work(batches)
        finally:
            trimmed()

    return run
