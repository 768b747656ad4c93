"""State that a Python worker keeps between the tasks it runs."""

from __future__ import annotations

import ctypes
import gc
import sys
from collections.abc import Callable, Iterator
from types import ModuleType

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def worker_state(slot: str, key: str, build: Callable[[], object]) -> object:
    """The object that this process has for ``slot`` and ``key``; any other object is let go first.

    The package's functions reach workers by value, so their module globals are copies; a module
    entry of the process itself is not.  A worker runs one function at a time, so one object per
    process is enough, and a long-lived worker holds no state of earlier stages.
    """
    home = sys.modules.setdefault("_worker_state", ModuleType("_worker_state")).__dict__
    if home.get("held", (None, None))[0] != (slot, key):
        home.pop("held", None)
        release_memory()
        home["held"] = ((slot, key), build())
    return home["held"][1]


def lean(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """A task without state of its own: it lets go what earlier tasks hold in this process, and gives back at its end what it has used."""

    def lean_run(batches: Iterator) -> Iterator:
        worker_state("none", "", lambda: None)
        yield from run(batches)
        release_memory()

    return lean_run


def release_memory() -> None:
    """Gives freed memory back to the system: unreachable objects, Arrow's pool, then the C heap where that is possible."""
    gc.collect()
    arrow = sys.modules.get("pyarrow")
    if arrow is not None:
        arrow.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def executors_give_back(spark: SparkSession) -> None:
    """The executors' JVMs collect and return the heap that earlier jobs have left unused; they keep it otherwise, beside what Python workers take next.

    As many tasks as there are cores, so that idle executors get one each; no result depends on it.
    """
    tasks = spark.sparkContext.defaultParallelism
    spark.range(0, tasks, 1, tasks).select(F.java_method(F.lit("java.lang.System"), F.lit("gc")).alias("gc")).write.format("noop").mode("overwrite").save()
