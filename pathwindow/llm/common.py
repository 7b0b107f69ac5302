"""Helpers shared by the corpus operators."""

from __future__ import annotations

import atexit
import ctypes
import ctypes.util
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Only where a session names none (unit tests on one machine) a fresh local folder is set.
    """
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="checkpoint-"))
        named = spark.sparkContext.getCheckpointDir()
    return named.rstrip("/")


_TIDIED: set[str] = set()


def run_dir(spark: SparkSession) -> str:
    """This application's part of the shared folder; it is deleted when the driver's Python ends in order."""
    path = f"{shared_dir(spark)}/corpus-{spark.sparkContext.applicationId}"
    if path not in _TIDIED:
        _TIDIED.add(path)
        atexit.register(_tidy, spark, path)
    return path


def _tidy(spark: SparkSession, path: str) -> None:
    if spark.sparkContext._jsc is not None and not spark.sparkContext._jsc.sc().isStopped():
        _delete(spark, path)


def _delete(spark: SparkSession, name: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(name)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


SHUFFLE_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
LISTS = "spark.sql.objectHashAggregate.sortBased.fallbackThreshold"


@contextmanager
def _set(spark: SparkSession, key: str, value: str) -> Iterator[None]:
    before = spark.conf.get(key)
    spark.conf.set(key, value)
    try:
        yield
    finally:
        spark.conf.set(key, before)


def shuffles_dropped(spark: SparkSession):
    """Within, a query's shuffle files go as soon as it ends; its rows are in a table by then."""
    return _set(spark, SHUFFLE_CLEANUP, "true")


def lists_hashed(spark: SparkSession):
    """Within, a task collects up to 20,000 short lists by hashing before it sorts; Spark's bound is 128."""
    return _set(spark, LISTS, "20000")


BATCH_BYTES, BATCH = "spark.sql.execution.arrow.maxBytesPerBatch", "8m"


def bounded_batches(spark: SparkSession) -> None:
    """From here on the session hands Python batches of 8 MB; rows alone would let long texts fill a worker's memory."""
    spark.conf.set(BATCH_BYTES, BATCH)


class Written:
    """A frame written as Parquet into the shared folder, and its path for a later drop."""

    def __init__(self, frame: DataFrame, tag: str):
        self.spark = frame.sparkSession
        self.path = f"{run_dir(self.spark)}/{tag}-{uuid.uuid4().hex}"
        bounded_batches(self.spark)
        with shuffles_dropped(self.spark):
            frame.write.parquet(self.path)
        self.frame = self.spark.read.schema(frame.schema).parquet(self.path)

    def drop(self) -> None:
        _delete(self.spark, self.path)


def written(frame: DataFrame, tag: str) -> DataFrame:
    """Cut the lineage of a frame by a table in the shared folder."""
    return Written(frame, tag).frame


def map_batches(
    frame: DataFrame, work: Callable[[pa.RecordBatch], Iterable[pa.RecordBatch]] | Callable, schema: str, setup: Callable[[], Callable] | None = None
) -> DataFrame:
    """``mapInArrow`` with one function a batch. With ``setup``, each task builds its function once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        each = setup() if setup else work
        try:
            for batch in batches:
                if batch.num_rows:
                    yield from each(batch)
        finally:
            trim()

    bounded_batches(frame.sparkSession)
    return frame.mapInArrow(run, schema)


def trim() -> None:
    """Give freed memory back to the system: Python workers live on after a task, beside those of the next stage."""
    pa.default_memory_pool().release_unused()
    libc = ctypes.util.find_library("c")
    give_back = getattr(ctypes.CDLL(libc), "malloc_trim", None) if libc else None
    if give_back:
        give_back(0)


def texts(batch: pa.RecordBatch, name: str = "text") -> list[str]:
    """The texts of a batch; a null counts as empty."""
    return [t or "" for t in batch.column(batch.schema.get_field_index(name)).to_pylist()]


def crc_fold(column: str, folds: int):
    """crc32 of the id written as text, modulo the number of folds."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % folds


def filter_batches(frame: DataFrame, setup: Callable[[], Callable[[list[str]], list[bool]]], text_col: str = "text") -> DataFrame:
    """The rows whose text a judgement built once a task lets stay, with all columns; nothing is shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        stays = setup()
        for batch in batches:
            if batch.num_rows:
                yield batch.filter(pa.array(stays(texts(batch, text_col)), pa.bool_()))

    bounded_batches(frame.sparkSession)
    return frame.mapInArrow(run, frame.schema)
