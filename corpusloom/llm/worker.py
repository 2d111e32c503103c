"""What a Python worker keeps between tasks: one operator's state at a time, so that stages that follow don't add up."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable
from typing import Any

import pyarrow as pa

_HELD: dict[str, Any] = {}
#: Rows of whole texts that cross to Python at once where a result is stored, which bounds buffers on both sides.
TEXTS = 1_000


def trim() -> None:
    """Gives freed memory back to the system."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library: it may keep what was freed
        return


def held(key: str, make: Callable[[], Any]) -> Any:
    """make()'s result, from the last task if that had the same key; any other state is dropped first."""
    if key not in _HELD:
        _HELD.clear()
        trim()
        _HELD[key] = make()
        trim()
    return _HELD[key]
