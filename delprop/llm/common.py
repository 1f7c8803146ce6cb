"""Helpers shared by the operators: tables, scratch storage, Arrow batches."""

from __future__ import annotations

import atexit
import ctypes
import gc
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

_SCRATCH: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_root(spark: SparkSession) -> str:
    """The shared folder the session names for checkpoints; a local one only where none is named and all runs in one process."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = held.get() if held.isDefined() else None
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("name a folder that all executors share in spark.checkpoint.dir")
        root = f"file://{tempfile.mkdtemp(prefix='delprop-')}"
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def _remove_scratch() -> None:
    spark = SparkSession.getActiveSession()
    while _SCRATCH and spark is not None:
        path = _SCRATCH.pop()
        try:
            jvm = spark.sparkContext._jvm
            at = jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
        except Exception:  # the session is going down anyway
            return


atexit.register(_remove_scratch)


#: Rows of one file of a scratch table of narrow rows.
FILE_ROWS = 1 << 20


def materialise(df: DataFrame, label: str, rows: int | None = None) -> DataFrame:
    """Cut the lineage with a Parquet table in the shared scratch folder (computed once, survives lost executors).

    ``rows`` bounds the number of (narrow) rows, if known: the shuffled table
    then has as many files as these need and at least eight, not one for each shuffle partition.
    """
    files = None if rows is None else max(8, -(-rows // FILE_ROWS))
    if files is not None and files < int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")):
        df = df.coalesce(files)
    path = f"{scratch_root(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _SCRATCH.append(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Emptied before a worker starts on another operator: name -> function.
WORKER_CACHES: dict[str, Callable[[], None]] = {}


def release_worker_memory(keep: str = "") -> None:
    """Python workers are reused; what an operator other than ``keep`` cached there goes back to the system."""
    if set(WORKER_CACHES) - {keep}:
        for name in set(WORKER_CACHES) - {keep}:
            WORKER_CACHES.pop(name)()
        gc.collect()
        try:
            ctypes.CDLL("libc.so.6").malloc_trim(0)
        except OSError:  # another C library: nothing to trim
            return


#: Bytes of one Arrow batch: texts may be long, and a worker holds a batch several times over.
BATCH_BYTES = 2 << 20


def bound_batches(spark: SparkSession) -> None:
    """Arrow batches close at ``BATCH_BYTES`` (or the session's number of rows); narrow rows hardly notice."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)


def map_arrow(df: DataFrame, kernel: Callable[[pa.RecordBatch], pa.RecordBatch], schema: str | StructType) -> DataFrame:
    """Apply ``kernel`` to every Arrow batch of ``df``, in batches of bounded bytes."""
    bound_batches(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release_worker_memory()
        for batch in batches:
            if batch.num_rows:
                yield kernel(batch)

    return df.mapInArrow(run, schema)


def keep_rows(df: DataFrame, judge: Callable[[list[str | None]], list[bool]]) -> DataFrame:
    """The rows of ``df`` whose text ``judge`` accepts, with all their columns."""
    return map_arrow(df, lambda batch: batch.filter(pa.array(judge(batch.column("text").to_pylist()), pa.bool_())), df.schema)


def unsigned_crc32(text: Column) -> Column:
    return F.crc32(F.coalesce(text, F.lit("")).cast("binary"))


def held_out(doc_id: Column) -> Column:
    """crc32 of the id as text, modulo five, is zero; a null id counts as held out, so it is never learnt from."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(True))


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def labelled_sample(documents: DataFrame, labels: DataFrame, target: str, bound: int) -> DataFrame:
    """At most about ``bound`` labelled training rows as (doc_id, text, label), spread by a hash of the id.

    Held-out ids and null labels never enter.  The labels are thinned before
    the join, so the broadcast side has at most ``bound`` rows (a few per
    cent more, since the thinning is by hash).
    """
    marks = (
        labels.select("doc_id", F.col(target).cast("int").alias("label"))
        .where(F.col("label").isNotNull() & ~held_out(F.col("doc_id")))
        .groupBy("doc_id")
        .agg(F.max("label").alias("label"))
    )
    total = marks.count()
    keep = min(1.0, bound / max(total, 1))
    spread = F.pmod(F.xxhash64(F.lit("train"), F.col("doc_id")), F.lit(1 << 30)) < F.lit(int(keep * (1 << 30)))
    texts = documents.select("doc_id", F.coalesce(F.col("text"), F.lit("")).alias("text"))
    return texts.join(F.broadcast(marks.where(spread)), "doc_id")
