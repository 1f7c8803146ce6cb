"""Tables in the shared folder the session names for checkpoints: computed once, safe from lost executors."""

from __future__ import annotations

import atexit
import gc
import re
import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession

_PATHS: list[str] = []
#: For :func:`stored`, where rows are megabytes long: the writer looks at the size of its group after every row, not after a hundred.
LONG_ROWS = {"compression": "none", "parquet.block.size": str(16 << 20), "parquet.page.size.row.check.min": "1"}


def root(spark: SparkSession) -> str:
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        named = held.get() if held.isDefined() else None
    if not named:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("name a folder that all executors share in spark.checkpoint.dir")
        named = f"file://{tempfile.mkdtemp(prefix='delprop-')}"
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


def new_path(spark: SparkSession, label: str) -> str:
    path = f"{root(spark)}/{label}-{uuid.uuid4().hex}"
    _PATHS.append(path)
    return path


def stored(df: DataFrame, label: str, **options: str) -> DataFrame:
    path = new_path(df.sparkSession, label)
    df.write.options(**options).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def dropped(df: DataFrame) -> None:
    """Delete a :func:`stored` table that is read no more."""
    for path in [p for p in _PATHS if any(f"{p.rsplit('/', 1)[-1]}/" in f for f in df.inputFiles()[:1])]:
        _PATHS.remove(path)
        _delete(df.sparkSession, path)


def settled(spark: SparkSession) -> None:
    """Have the driver collect its garbage: shuffle files of frames that are gone go with them, and unused heap goes back.

    Once more after a while: the JVM learns of frames that Python has let go while it collects for the first time.
    """
    for pause in (0.3, 0.0):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(pause)


def _delete(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def _clear() -> None:
    spark = SparkSession.getActiveSession()
    while _PATHS and spark is not None:
        path = _PATHS.pop()
        try:
            _delete(spark, path)
        except Exception:  # the session is going down anyway
            return


atexit.register(_clear)
