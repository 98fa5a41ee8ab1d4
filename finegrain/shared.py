"""Tables in the folder that all executors share, which cut lineage and survive lost executors."""

from __future__ import annotations

import atexit
import re
import sys
import tempfile
import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from typing import TypeVar

from pyspark import cloudpickle, inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession

# Executors need not have this package installed: its functions travel with the tasks.
cloudpickle.register_pickle_by_value(sys.modules[__package__])

T = TypeVar("T")

_tables: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir; a folder of this machine where that is unset and executors are threads of the driver."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        if not re.fullmatch(r"local(\[[^\[]*\])?", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="checkpoints-"))
    return sc._jsc.sc().getCheckpointDir().get()


def table(df: DataFrame) -> DataFrame:
    """df written to the shared folder and read again; removed when the driver ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/cells-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    _tables.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def forget_later(spark: SparkSession, path: str) -> None:
    """Remove files when the driver ends."""
    _tables.append((spark, path))


def together(jobs: list[Callable[[], T]], at_once: int = 6) -> list[T]:
    """The results of independent jobs, in order; several run at a time, as small fits leave most of a cluster idle."""
    if len(jobs) < 2:
        return [job() for job in jobs]
    session = SparkSession.getActiveSession()
    own = inheritable_thread_target(session) if session else inheritable_thread_target  # jobs keep the caller's tags and properties
    with ThreadPoolExecutor(min(at_once, len(jobs))) as pool:
        return [f.result() for f in [pool.submit(own(job)) for job in jobs]]


@atexit.register
def _clean() -> None:
    for spark, path in _tables:
        try:
            target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
        except Exception:  # the JVM may have ended first
            return
