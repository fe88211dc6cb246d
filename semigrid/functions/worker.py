"""State that lives as long as a Python worker, for bounded caches and loaded models."""

from __future__ import annotations

import sys
import types
from collections.abc import Callable, Iterator
from functools import wraps
from typing import Any


def _store() -> dict[str, Any]:
    return sys.modules.setdefault("_semigrid_worker_state", types.ModuleType("_semigrid_worker_state")).__dict__.setdefault("held", {})


def worker_state(key: str, make: Callable[[], Any]) -> Any:
    """The object made by ``make`` the first time this worker process asked for ``key``."""
    store = _store()
    if key not in store:
        store[key] = make()
    return store[key]


def _give_back() -> None:
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass  # another C library


def lean(run: Callable, *uses: str) -> Callable:
    """``run`` over batches, for workers that go from one stage to the next.

    When a task begins, the worker forgets all state but that under the keys ``uses``, so no
    stage pays for the models of another; when it ends, free memory goes back to the system.
    """

    @wraps(run)
    def inner(batches: Iterator) -> Iterator:
        store = _store()
        gone = [k for k in store if k not in uses]
        for k in gone:
            del store[k]
        if gone:
            _give_back()
        yield from run(batches)
        _give_back()

    return inner


def small_batches(spark, size: int = 4 << 20) -> None:
    """From now on, batches sent to Python end at about so many bytes, however long the texts are.

    The setting is one that may change at run time. It stays, because a plan that is returned
    is run by whoever asked for it.
    """
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    if int(spark.conf.get(key).rstrip("b")) > size:
        spark.conf.set(key, size)
