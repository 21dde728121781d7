"""Small helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space, as the operators' contracts define it.
WS = r"[ \t-\r]"
WORD = r"[^ \t-\r]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; one of the machine's own only where Spark runs on one machine alone."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named is None and not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return (named or "/tmp/checkpoints").rstrip("/")


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut lineage with a reliable checkpoint in the folder the cluster names."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


#: Rows of hashes and ids (some tens of bytes each) up to which a counted side of a join is broadcast.
BROADCAST_ROWS = 1_000_000


def broadcast_if_small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """df (checkpointed: it is counted first) for a broadcast, or as it is if it has more rows."""
    return F.broadcast(df) if df.count() <= rows else df


def text_or_empty(text: Column) -> Column:
    return F.coalesce(text.cast("string"), F.lit(""))


def word_count(text: Column) -> Column:
    return F.regexp_count(text_or_empty(text), F.lit(WORD)).cast("long")


def crc_bucket(doc_id: Column, n: int) -> Column:
    """crc32 of the id written as text, modulo n; a null id counts as empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % n


_kept: dict[str, object] = {}


def one_per_worker(tag: str, make):
    """A worker's model or codec by tag; making another one lets the last go, so caches never add up."""
    if tag not in _kept:
        _kept.clear()
        _kept[tag] = make()
    return _kept[tag]


def drop_shuffles(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of plans that nothing refers to any more."""
    gc.collect()
    spark._jvm.System.gc()


def forget_model() -> None:
    _kept.clear()


def return_memory() -> None:
    """Give the system what this process has freed; allocators keep it otherwise, and idle workers with them."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc only
    if trim:
        trim(0)


#: Rows turned into Python objects at a time.
ROWS = 512


def in_slices(batch: pa.RecordBatch, rows: int = ROWS) -> Iterator[pa.RecordBatch]:
    """The batch some rows at a time (an empty one as it is), so that a task never holds a whole batch twice over."""
    for at in range(0, max(batch.num_rows, 1), rows):
        yield batch.slice(at, rows)


def freed(run: Callable, model: bool = False) -> Callable:
    """``run`` for mapInArrow with nothing left behind: the worker's model of an earlier stage goes unless this
    one uses a model, and what the task freed goes back to the system at its end."""

    def out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not model:
            forget_model()
        try:
            yield from run(batches)
        finally:
            return_memory()

    return out
