"""A session with the settings that the engine is tuned for; every operator works with any session it is given."""

from __future__ import annotations

from pyspark.sql import SparkSession

RUNTIME = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.session.timeZone": "UTC",
    "spark.sql.execution.arrow.pyspark.enabled": "true",
}


def session(master: str | None = None, shuffle_partitions: int | None = None, **conf: str) -> SparkSession:
    """Get or create a session. Beyond a laptop leave ``shuffle_partitions`` alone: about 128 MB of shuffle each is right."""
    builder = SparkSession.builder.appName("finegrain").config(map=RUNTIME | conf)
    if master:
        builder = builder.master(master)
    if shuffle_partitions:
        builder = builder.config("spark.sql.shuffle.partitions", shuffle_partitions)
    return builder.getOrCreate()
