"""Tables that cut lineage: written Parquet in the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_SETTING = "spark.checkpoint.dir"
#: Paths written inside open scratch() blocks, innermost last.
_OPEN: list[list[str]] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder named in spark.checkpoint.dir; a temporary one only where the setting is absent and all tasks run in the driver (local tests)."""
    found = spark.conf.get(_SETTING, None) or spark.sparkContext.getConf().get(_SETTING)
    if not found:
        found = getattr(spark.sparkContext, "_pathloom_folder", None)
        if not found:
            if not spark.sparkContext.master.startswith("local"):
                raise ValueError(f"set {_SETTING} to a folder that the driver and all executors share")
            found = spark.sparkContext._pathloom_folder = "file://" + tempfile.mkdtemp(prefix="pathloom-")
    return found.rstrip("/")


def _hadoop(spark: SparkSession, path: str):
    """The file system of a path, and the path as it knows it."""
    there = spark._jvm.org.apache.hadoop.fs.Path(path)
    return there.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()), there


def new_path(spark: SparkSession, name: str, lasting: bool = False) -> str:
    """A path for a table. An open scratch() block deletes what stands there at its end, unless it is lasting."""
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    if _OPEN and not lasting:
        _OPEN[-1].append(path)
    return path


def written(df: DataFrame, name: str, lasting: bool = False) -> DataFrame:
    """The rows of df, computed once and read back from the shared folder: a lost executor costs no recomputation. The table goes with the
    application, or with an open scratch() block unless it is lasting, as tables that a graph keeps for later queries are."""
    spark = df.sparkSession
    path = new_path(spark, name, lasting)
    try:
        df.write.parquet(path)
    finally:
        files, there = _hadoop(spark, path)
        files.deleteOnExit(there)
    return spark.read.schema(df.schema).parquet(path)


def forget(*frames: DataFrame) -> None:
    """Delete tables that written() made and that no later step reads."""
    for df in frames:
        for file in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            files, there = _hadoop(df.sparkSession, file)
            files.delete(there, True)


def stored_size(df: DataFrame) -> int:
    """Bytes of the files that a table is read from."""
    total = 0
    for file in df.inputFiles():
        files, there = _hadoop(df.sparkSession, file)
        total += files.getFileStatus(there).getLen()
    return total


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Delete all tables written inside the block at its end; results of the block must be read in it."""
    _OPEN.append([])
    try:
        yield
    finally:
        for path in _OPEN.pop():
            files, there = _hadoop(spark, path)
            files.delete(there, True)


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner delete shuffle files of plans that nothing refers to any more; it acts on the driver's garbage collections."""
    import gc

    gc.collect()
    spark._jvm.System.gc()
