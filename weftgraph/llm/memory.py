"""Give memory back at the end of a task, since Python workers are used again."""

from __future__ import annotations

import ctypes
import gc
import sys
from collections.abc import Callable

import pyarrow as pa

#: What frees the memories that operators keep from task to task in this process, by operator.
_keeps: dict[str, Callable[[], None]] = {}


def keep(operator: str, free: Callable[[], None]) -> None:
    """Tell what frees the operator's memory when a task of another operator begins here."""
    _keeps[operator] = free


def make_room(operator: str) -> None:
    """Free what other operators keep in this process; called when a task begins."""
    others = [o for o in _keeps if o != operator]
    for o in others:
        _keeps.pop(o)()
    if others:
        give_back()


def give_back() -> None:
    """Free what the task left: garbage, Arrow's pool, and free pages of the C heap (Linux)."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    if sys.platform == "linux":
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
        if trim is not None:
            trim(0)
