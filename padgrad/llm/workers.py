"""Memory of executors and their Python workers, which Spark keeps from stage to stage."""

from __future__ import annotations

import ctypes
import gc
import sys

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

_stage = ""


def tidy(stage: str) -> None:
    """At a worker's first task of ``stage``: lets go of other stages' caches and gives free memory back to the system."""
    global _stage
    if _stage == stage:
        return
    _stage = stage
    for module, cache in (("tokenizing", "_open"), ("context_tree", "_tables")):
        if (loaded := sys.modules.get(f"padgrad.llm.{module}")) is not None:
            getattr(loaded, cache).clear()
    gc.collect()
    pa.default_memory_pool().release_unused()
    if hasattr(libc := ctypes.CDLL(None), "malloc_trim"):  # glibc
        libc.malloc_trim(0)


def shrink_heaps(spark: SparkSession) -> None:
    """Executors collect their garbage and give free heap back to the system, so that what earlier stages let it grow to is not held beside this stage's Python workers.

    A task for each core; an executor that is busy or gets none only stays as it is. Results never depend on it.
    """
    n = spark.sparkContext.defaultParallelism
    spark.range(0, n, 1, n).select(F.reflect(F.lit("java.lang.System"), F.lit("gc"))).collect()  # a null for each
