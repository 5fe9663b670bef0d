"""What bounds the memory that Python and its Arrow batches take on an executor.

By default a batch for Python ends at 10,000 rows, however long their texts, and
stands in the JVM's own memory, on its way and in the worker at once.
``small_batches`` ends it by bytes as well. Workers live on between stages, and
their allocators keep what they once had: ``lean`` gives that back.
"""

from __future__ import annotations

import ctypes
import sys
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import SparkSession

BATCH_BYTES = 4 << 20
_SETTING = "spark.sql.execution.arrow.maxBytesPerBatch"


def small_batches(spark: SparkSession, most: int = BATCH_BYTES) -> None:
    """From now on Arrow batches of the session end by ``most`` bytes; a smaller bound or one of rows stays.

    A row is never cut: a longer one is a batch by itself.
    """
    now = spark.conf.get(_SETTING, None)
    if not now or now.startswith("-") or spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(now) > most:
        spark.conf.set(_SETTING, str(most))


def give_back() -> None:
    """Return what this process's allocators hold free to the system."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc only
    if trim:
        trim(0)


def lean(run: Callable[[Iterator], Iterator], vocabulary: bool = False) -> Callable[[Iterator], Iterator]:
    """``run`` for ``mapInArrow``, after which its worker keeps no free memory.

    Unless ``run`` needs a ``vocabulary``, the worker first drops any that an
    earlier stage left there.
    """

    def ran(batches):
        tokens = sys.modules.get(f"{__package__}.tokens")
        if tokens and not vocabulary:
            tokens._made.clear()
        yield from run(batches)
        give_back()

    return ran
