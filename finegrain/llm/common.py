"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import atexit
import re
import sys
import tempfile
import uuid

from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# Executors need not have this package installed: its functions travel with the tasks.
cloudpickle.register_pickle_by_value(sys.modules[__package__])

# Words of the contracts are runs of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"

BATCH_ROWS, BATCH_BYTES = 2000, 8 << 20

_written: list[tuple[SparkSession, str]] = []


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return bounded(spark.read.parquet(f"{sf_dir}/{table}.parquet"))


def bounded(df: DataFrame) -> DataFrame:
    """df, whose session from now on sends Python BATCH_BYTES or BATCH_ROWS at a time at most.

    By default a batch has 10,000 rows however long they are, and memory for batches outside the heap isn't given back.
    """
    conf = df.sparkSession.conf
    for key, most in (("maxRecordsPerBatch", BATCH_ROWS), ("maxBytesPerBatch", BATCH_BYTES)):
        number, unit = re.fullmatch(r"(-?\d+)([kmg]?)b?", conf.get(f"spark.sql.execution.arrow.{key}").lower()).groups()
        now = int(number) << {"": 0, "k": 10, "m": 20, "g": 30}[unit]
        if now <= 0 or now > most:
            conf.set(f"spark.sql.execution.arrow.{key}", str(most))
    return df


def free_name(name: str, taken: list[str]) -> str:
    """name, with as many underscores as keep it apart from the names that are taken (in whichever case)."""
    low = {x.lower() for x in taken}
    while name.lower() in low:
        name += "_"
    return name


def free_prefix(taken: list[str]) -> str:
    """Underscores that none of the names begins with: names of one's own with this prefix clash with none of them."""
    prefix = "_"
    while any(x.startswith(prefix) for x in taken):
        prefix += "_"
    return prefix


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def n_bytes(name: str = "text") -> Column:
    return F.octet_length(text_or_empty(name)).cast("long")


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


def written(df: DataFrame) -> DataFrame:
    """df as a table in the shared folder: lineage ends there, and a lost executor costs no earlier stage.

    The files go when the driver's Python ends; ``drop`` removes them sooner.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/table-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    _written.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._finegrain_path = path
    return out


def _remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def drop(df: DataFrame) -> None:
    """Remove a table of ``written`` that nothing reads any more."""
    _remove(df.sparkSession, df._finegrain_path)
    _written[:] = [x for x in _written if x[1] != df._finegrain_path]


@atexit.register
def _clean() -> None:
    for spark, path in _written:
        try:
            _remove(spark, path)
        except Exception:  # the JVM may have ended first
            return


def bucket_count(total: int, each: int) -> int:
    """So many buckets that each gets about ``each`` of ``total``."""
    return max(8, -(-int(total or 0) // each))
