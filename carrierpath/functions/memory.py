"""Memory of Python workers, which Spark keeps for later tasks."""

from __future__ import annotations

import ctypes

import pyarrow as pa

#: Bytes from which a block of memory is the system's own and goes back when it is freed; smaller ones are used again, up to ``SPARE`` bytes of free memory.
LARGE, SPARE = 1 << 23, 1 << 26
_M_TRIM_THRESHOLD, _M_MMAP_THRESHOLD = -1, -3
_held: list = []


def lean() -> None:
    """From now on this process returns large blocks as soon as they are freed, those of Arrow too; without glibc nothing changes."""
    if not _held:
        try:
            libc = ctypes.CDLL(None)
            libc.mallopt(_M_MMAP_THRESHOLD, LARGE)
            libc.mallopt(_M_TRIM_THRESHOLD, SPARE)
            libc.malloc_trim  # noqa: B018
            pa.set_memory_pool(pa.system_memory_pool())
        except (AttributeError, OSError):
            libc = None
        _held.append(libc)


def trim() -> None:
    """Returns what is freed of small blocks."""
    lean()
    if _held[0] is not None:
        _held[0].malloc_trim(0)


def trimmed(run):
    """``run`` of a map over Arrow batches, in a worker that keeps no memory beyond its task."""

    def inner(batches):
        lean()
        try:
            yield from run(batches)
        finally:
            trim()

    return inner
