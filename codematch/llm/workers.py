"""Memory of Python workers: idle ones stay alive, and should hold none."""

from __future__ import annotations

import ctypes

import pyarrow as pa


def give_back() -> None:
    """Return memory that is no longer needed to the system."""
    pa.default_memory_pool().release_unused()
    getattr(ctypes.CDLL(None), "malloc_trim", lambda _: 0)(0)


def released(run):
    """run over batches, and give_back at the end."""

    def whole(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return whole
