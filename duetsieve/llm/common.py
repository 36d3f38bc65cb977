"""Helpers shared by the corpus operators: reading, checkpoints, Arrow text batches."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster shares for checkpoints; a temporary one only where it is unset and all is one machine."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not found:
        kept = spark.sparkContext._jsc.sc().getCheckpointDir()
        if kept.isDefined():
            return kept.get()
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        found = "file://" + tempfile.mkdtemp(prefix="duetsieve-")
        spark.sparkContext.setCheckpointDir(found)
    return found


_CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextlib.contextmanager
def setting(spark: SparkSession, key: str, value: str) -> Iterator[None]:
    """A setting of the session that holds for what runs inside."""
    before = spark.conf.get(key, None)
    spark.conf.set(key, value)
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, before)


def saved(df: DataFrame, name: str) -> DataFrame:
    """``df`` written once to the shared folder and read back: later plans start from files that outlive executors.

    The shuffle files of the write go when it ends; ``df`` itself is not executed again.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/duetsieve-{name}-{uuid.uuid4().hex}"
    with setting(spark, _CLEAN, "true"):
        df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.saved_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Removes ``saved`` tables from which nothing will be read again."""
    for t in tables:
        jvm = t.sparkSession.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(t.saved_at)
        where.getFileSystem(t.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


_KEPT: dict[str, object] = {}


def kept(run: str, make: Callable[[], object]) -> object:
    """What this worker keeps from task to task of one run of a query; nothing is kept of other runs."""
    if run not in _KEPT:
        _KEPT.clear()
        _KEPT[run] = make()
    return _KEPT[run]


def _give_back() -> None:
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of the GNU library
    if trim:
        trim(0)


def _others_go(run: str) -> None:
    if _KEPT.keys() - {run}:
        _KEPT.clear()
        _give_back()


def lean(work: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], run: str = "") -> Callable:
    """``work``, after which the Python worker gives the memory that it has freed back: workers wait, reused, beside later stages.

    What the worker kept for another run than ``run`` goes before ``work`` begins.
    """

    def begun(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _others_go(run)  # of this module: ``begun`` travels by value, with copies of the values that it names
        try:
            yield from work(batches)
        finally:
            _give_back()

    return begun


def text_array(column: pa.Array) -> pa.LargeStringArray:
    """Texts with nulls as empty strings."""
    if pa.types.is_null(column.type):
        return pa.array([""] * len(column), pa.large_string())
    return pc.fill_null(column.cast(pa.large_string()), "")


def text_lists(batches: Iterator[pa.RecordBatch], column: str = "text") -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    for batch in batches:
        if batch.num_rows:
            yield batch, text_array(batch.column(column)).to_pylist()
