"""Keeps Python workers small: freed blocks go back to the system at once.

Workers live on between stages, so what an allocator holds back adds up beside the
next stage's workers.
"""

from __future__ import annotations

import ctypes

import pyarrow as pa

#: glibc's parameters: blocks from this size on are mapped, and so unmapped when freed.
M_TRIM_THRESHOLD, M_MMAP_THRESHOLD, BLOCK = -1, -3, 1 << 18

try:
    _libc = ctypes.CDLL("libc.so.6")
except OSError:  # another C library: its own behaviour is kept
    _libc = None


def keep_small() -> None:
    if _libc is not None:
        _libc.mallopt(M_MMAP_THRESHOLD, BLOCK)
        _libc.mallopt(M_TRIM_THRESHOLD, BLOCK)
    pa.set_memory_pool(pa.system_memory_pool())


def trim() -> None:
    if _libc is not None:
        _libc.malloc_trim(0)
