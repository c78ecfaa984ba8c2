"""What Python workers hold: one large object at a time, and nothing once a task has ended.

Workers are reused by later stages.  A large table must not stay beside those of
the next operator, nor in an idle worker while the JVM needs the memory.
"""

from __future__ import annotations

import ctypes
import ctypes.util
import functools
import gc
from collections.abc import Callable, Hashable, Iterator
from typing import Any

import pyarrow as pa
from pyspark.sql import SparkSession

#: Rows of whole texts in one Arrow batch.
BATCH_ROWS = 1_000

_held: dict[Hashable, Any] = {}


def only(key: Hashable, build: Callable[[], Any]) -> Any:
    """The worker's object of that key; any other is dropped before it is built."""
    if key not in _held:
        if _held:
            _held.clear()
            trim()
        _held[key] = build()
    return _held[key]


def release() -> None:
    """An idle worker holds no tables, and freed memory goes back."""
    _held.clear()
    trim()


def released(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """``run`` over the batches of a task, with a release at its end, also after an error."""

    @functools.wraps(run)
    def task(batches: Iterator) -> Iterator:
        try:
            yield from run(batches)
        finally:
            release()

    return task


def trim() -> None:
    """Give freed memory back to the system, where the C library can."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    libc = ctypes.CDLL(ctypes.util.find_library("c"))
    if hasattr(libc, "malloc_trim"):
        libc.malloc_trim(0)


def limit_batches(spark: SparkSession, rows: int = BATCH_ROWS) -> None:
    """Lower the rows of an Arrow batch for this session: texts can be long, and a
    batch is held by the JVM and by the worker at one time.  The plans that the
    operators return run after they return, so the setting stays."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(key))
    if now <= 0 or now > rows:
        spark.conf.set(key, str(rows))
