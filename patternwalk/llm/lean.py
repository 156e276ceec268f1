"""Workers that give memory back: one serves many tasks, and what a task has freed counts until it is returned to the system."""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import SparkSession

#: Rows of texts, or of sets of shingles, that go to a worker at once; a task holds a batch several times, in the JVM and in its worker.
ROWS = 1024
_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"

#: By operator: how to drop what its tasks keep in a worker for its next ones.
_KEPT: dict[str, Callable[[], None]] = {}


def keeps(operator: str, drop: Callable[[], None]) -> None:
    _KEPT[operator] = drop


def make_room(operator: str) -> None:
    """What other operators keep in this worker goes."""
    for other, drop in _KEPT.items():
        if other != operator:
            drop()


@contextlib.contextmanager
def small_batches(spark: SparkSession) -> Iterator[None]:
    """Queries that run in here send workers at most ``ROWS`` rows at once."""
    before = spark.conf.get(_BATCH)
    spark.conf.set(_BATCH, str(ROWS))
    try:
        yield
    finally:
        spark.conf.set(_BATCH, before)


def give_back() -> None:
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):
        pass  # another C library; it keeps what it has


def tidily(run: Callable[[Iterator], Iterator], operator: str = "") -> Callable[[Iterator], Iterator]:
    """A task's function that first makes other operators give room and gives memory back when its rows are through."""

    def whole(batches: Iterator) -> Iterator:
        make_room(operator)
        yield from run(batches)
        give_back()

    return whole
