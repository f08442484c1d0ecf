"""Broadcast of objects of this package to workers that need no copy of the package."""

from __future__ import annotations

import ctypes
import pickle
from contextlib import contextmanager

import pyarrow as pa
from pyspark import cloudpickle


def ship(spark, thing):
    return spark.sparkContext.broadcast(cloudpickle.dumps(thing))


def landed(shared):
    """The object; a worker unpacks it once and keeps it from task to task, until Spark takes the broadcast away."""
    if not hasattr(shared, "_unpacked"):
        shared._unpacked = pickle.loads(shared.value)
        shared.__dict__.pop("_value", None)  # the packed bytes
    return shared._unpacked


def portions(batches, rows: int = 1000):
    """Batches in slices, so that a task holds the texts of a few rows as objects at a time."""
    for b in batches:
        for k in range(0, b.num_rows, rows):
            yield b.slice(k, rows)


@contextmanager
def small_batches(spark, rows: int = 1000):
    """What is written meanwhile goes to Python workers in batches of so many rows; the session's own setting comes back then."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    own = spark.conf.get(name)
    spark.conf.set(name, rows)
    try:
        yield
    finally:
        spark.conf.set(name, own)


def trim() -> None:
    """Give freed memory back to the system: a worker goes from stage to stage, and allocators keep what the last one freed."""
    pa.default_memory_pool().release_unused()
    give = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc's
    if give:
        give(0)
