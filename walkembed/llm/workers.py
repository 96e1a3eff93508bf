"""Memory of Python workers, which Spark reuses from task to task and operator to operator.

A cache that speeds up one operator's next task must not stay when another
operator takes the worker over.
"""

from __future__ import annotations

import gc
from collections.abc import Callable

import pyarrow as pa

_caches: dict[str, Callable[[], None]] = {}
_owner: list[str] = [""]


def keep_cache(owner: str, clear: Callable[[], None]) -> None:
    _caches[owner] = clear


def take_over(owner: str) -> None:
    """Called as an operator's task begins: empties what other operators left in this worker."""
    if _owner[0] != owner:
        _owner[0] = owner
        for name in [n for n in _caches if n != owner]:
            _caches.pop(name)()
        gc.collect()
        pa.default_memory_pool().release_unused()
