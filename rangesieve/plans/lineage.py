"""Tables that cut a plan in two: written once to the folder that all executors share, read by every later step."""

from __future__ import annotations

import atexit
import gc
import re
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_written: list[str] = []
_hooked: list[bool] = []


def shared_folder(spark: SparkSession) -> str:
    """The session's checkpoint folder; where none is set, a single process may use one of its own, and a cluster may not."""
    context = spark.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        folder = spark.conf.get("spark.checkpoint.dir", None) or context.getConf().get("spark.checkpoint.dir")
        if folder is None and not re.fullmatch(r"local(\[[^\]]*\])?", context.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="checkpoint-"))
    return context._jsc.sc().getCheckpointDir().get()


def written(df: DataFrame) -> DataFrame:
    """df as a table in the shared folder, which goes when the driver ends."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if not _hooked:
        atexit.register(_clear, spark)
        _hooked.append(True)
    _written.append(path)
    return spark.read.schema(df.schema).parquet(path)


@contextmanager
def released(spark: SparkSession) -> Iterator[None]:
    """Tables written inside go at the end, and so do the shuffles of plans that nothing refers to any more."""
    before = len(_written)
    try:
        yield
    finally:
        _delete(spark, _written[before:])
        del _written[before:]
        # Spark drops the files of a shuffle when its plan is collected
        gc.collect()
        spark.sparkContext._jvm.System.gc()


def _clear(spark: SparkSession) -> None:
    context = spark.sparkContext
    if context._jsc is None or context._jsc.sc().isStopped():
        return
    _delete(spark, _written)


def _delete(spark: SparkSession, paths: list[str]) -> None:
    context = spark.sparkContext
    for path in paths:
        at = context._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(context._jsc.hadoopConfiguration()).delete(at, True)
