"""Bounded memory in Python workers, which live on from stage to stage and share their executor's bound.

Batches are bounded in bytes, not only in rows, so long texts do not pile up; a worker holds the look-up tables of one
operator at a time; memory freed after a batch goes back to the system.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable
from typing import TypeVar

import pyarrow as pa
from pyspark.sql import DataFrame

T = TypeVar("T")
BATCH_BYTES = 4 << 20
_SETTING = "spark.sql.execution.arrow.maxBytesPerBatch"
_held: dict[str, object] = {}


def small_batches(df: DataFrame) -> DataFrame:
    """``df``, in a session whose Arrow batches hold about ``BATCH_BYTES`` at most (a runtime option, lowered only)."""
    conf = df.sparkSession.conf
    now = conf.get(_SETTING).lower().rstrip("b")
    if not now.isdigit() or not 0 < int(now) <= BATCH_BYTES:
        conf.set(_SETTING, str(BATCH_BYTES))
    return df


def held(key: str, make: Callable[[], T]) -> T:
    """The tables ``key`` of this worker, made on first use; another operator's are let go first."""
    if key not in _held:
        let_go()
        _held[key] = make()
    return _held[key]  # type: ignore[return-value]


def let_go() -> None:
    """Drop whatever tables an earlier stage has left in this worker."""
    if _held:
        _held.clear()
        give_back()


def give_back() -> None:
    """Return freed memory of a batch to the system."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):
        return
