"""Tables that cut lineage, as in the rest of the library, and the memory that Python workers and the batches sent to them take."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import SparkSession

from ..sources.store import forget, new_path, release, shared_folder, written

__all__ = ["forget", "lean", "new_path", "release", "shared_folder", "small_batches", "written"]

#: Bytes of a batch, beyond which Spark ends it; one longer row is a batch of its own.
BATCH_BYTES = 4 << 20
_SETTING = "spark.sql.execution.arrow.maxBytesPerBatch"


def small_batches(spark: SparkSession) -> None:
    """Bound the batches sent to Python by bytes, in this session: 10,000 long texts in one buffer are copied on both sides, outside the heap. A lower bound stays."""
    found = spark.conf.get(_SETTING, None)
    if found is None or spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(found) > BATCH_BYTES:
        spark.conf.set(_SETTING, str(BATCH_BYTES))


def lean(step: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """The step of a Python worker that gives freed memory back when its task ends: the process waits for tasks of other stages."""

    def run(batches: Iterator) -> Iterator:
        try:
            yield from step(batches)
        finally:
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of the GNU library alone
            if trim is not None:
                trim(0)

    return run
