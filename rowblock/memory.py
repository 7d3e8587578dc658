"""Memory of Python processes that Spark keeps for later tasks."""

from __future__ import annotations

import ctypes
import ctypes.util

import pyarrow as pa


def give_back() -> None:
    """Return memory that is no longer used to the system, as far as it offers that."""
    pa.default_memory_pool().release_unused()
    libc = ctypes.util.find_library("c")
    trim = getattr(ctypes.CDLL(libc), "malloc_trim", None) if libc else None
    if trim:
        trim(0)
