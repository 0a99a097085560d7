"""What a Python worker holds between tasks: one operator's caches at most, and no freed pages."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Hashable
from typing import Any

import pyarrow as pa

_TRIM = getattr(ctypes.CDLL(None), "malloc_trim", None)
_KEPT: dict[Hashable, Any] = {}


def release() -> None:
    """Gives the pages that a batch has freed back to the system; a worker lives on through many tasks."""
    pa.default_memory_pool().release_unused()
    if _TRIM is not None:
        _TRIM(0)


def kept(key: Hashable, make: Callable[[], Any]) -> Any:
    """What make() gave when this process first asked for key; tasks that ask for another key take its place."""
    if key not in _KEPT:
        fresh()
        _KEPT[key] = make()
    return _KEPT[key]


def fresh() -> None:
    """Drops what tasks of other operators have kept; for tasks that keep nothing themselves."""
    if _KEPT:
        _KEPT.clear()
        release()
