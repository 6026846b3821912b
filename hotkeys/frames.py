"""Frames that several parts of a query read, kept until the next query releases them."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame

_KEPT: list[DataFrame] = []


def keep(frame: DataFrame) -> DataFrame:
    """Persist a frame on memory and disk; lost parts are computed again."""
    _KEPT.append(frame.persist(StorageLevel.MEMORY_AND_DISK))
    return _KEPT[-1]


def drop(frame: DataFrame) -> None:
    """Release one kept frame."""
    frame.unpersist()
    _KEPT[:] = [f for f in _KEPT if f is not frame]


def release() -> None:
    """Release all kept frames; those that are still used are computed again."""
    while _KEPT:
        _KEPT.pop().unpersist()
