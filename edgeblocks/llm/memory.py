"""Memory of Python workers, which outlive their tasks."""

from __future__ import annotations

import ctypes
import gc

import pyarrow as pa


def give_back() -> None:
    """Hands memory that a finished task no longer needs back to the system; a worker that waits for its next task would keep it beside the
    executor's own heap."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)
