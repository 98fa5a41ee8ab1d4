"""Views kept up to date from a stream of events, and fits that go on from the last one."""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable, Iterator
from typing import Any

import numpy as np
import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from finegrain import shared
from finegrain.sources.tables import load


def event_stream(spark: SparkSession, folder: str, files_each: int = 1) -> DataFrame:
    """The parquet files of a folder as a stream, a few files each trigger."""
    schema = spark.read.parquet(folder).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_each).parquet(folder)


def with_time(events: DataFrame) -> DataFrame:
    """ts as a timestamp that windows and watermarks take."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def replay_files(spark: SparkSession, sf_dir: str, folder: str, parts: int = 4, late_days: int = 3) -> None:
    """events as files in the order of ts, one of them late by some days: a fixture for streams."""
    events = load(spark, sf_dir, "events")
    for p in range(parts):
        own = events.where(F.pmod("event_id", F.lit(parts)) == p)
        if p == parts - 1:
            own = own.withColumn("ts", (F.col("ts").cast("timestamp") - F.expr(f"INTERVAL {late_days} DAYS")).cast("timestamp_ntz"))
        own.coalesce(1).sortWithinPartitions("ts").write.mode("append").parquet(folder)


def stream_temporal(events: DataFrame, width: str = "7 days", slide: str | None = None, watermark: str = "2 days") -> DataFrame:
    """user bucket x event type x period: tumbling, or sliding periods that overlap."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    rows = with_time(events).withWatermark("ts", watermark)
    grouped = rows.groupBy(window.alias("w"), F.pmod("user_id", F.lit(50)).alias("i"), F.col("event_type").alias("j"))
    return grouped.agg(F.sum("value").alias("v"), F.count("*").alias("n")).select("i", "j", F.col("w.start").alias("start"), "v", "n")


def stream_contemporaneous(events: DataFrame, groups: int = 5, watermark: str = "2 days") -> DataFrame:
    """user group x event type x day."""
    rows = with_time(events).withWatermark("ts", watermark)
    day = F.window("ts", "1 day")
    return rows.groupBy(day.alias("w"), F.pmod("user_id", F.lit(groups)).alias("i"), F.col("event_type").alias("j")).agg(F.sum("value").alias("v")).select("i", "j", F.col("w.start").alias("day"), "v")


def stream_sessions(events: DataFrame, gap: str = "6 hours", watermark: str = "2 days") -> DataFrame:
    """A user's sessions: where the timeline has gaps."""
    rows = with_time(events).withWatermark("ts", watermark)
    return rows.groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n")


def stream_deduplicated(events: DataFrame, watermark: str = "2 days") -> DataFrame:
    """Events once each, as long as repeats come within the watermark."""
    return with_time(events).withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def stream_mean(events: DataFrame, width_days: int = 7, groups: int = 5, watermark: str = "2 days") -> DataFrame:
    """The mean of both views' even shares, online: closed periods joined with the closed days in them of their bucket's group.

    Rows are timed by the last instant of their window, which carries the events' watermark on to the join.
    """
    rows = with_time(events).withWatermark("ts", watermark)
    kind = F.col("event_type")
    t = rows.groupBy(F.window("ts", f"{width_days} days"), F.pmod("user_id", F.lit(50)).alias("bucket"), kind.alias("tj")).agg(F.sum("value").alias("vt"))
    c = rows.groupBy(F.window("ts", "1 day"), F.pmod("user_id", F.lit(groups)).alias("grp"), kind.alias("cj")).agg(F.sum("value").alias("vc"))
    t = t.select("bucket", "tj", "vt", F.window_time("window").alias("last"))
    c = c.select("grp", "cj", "vc", F.col("window.start").alias("day"), F.window_time("window").alias("then"))
    within = (F.col("then") > F.col("last") - F.expr(f"INTERVAL {width_days} DAYS")) & (F.col("then") <= F.col("last"))
    both = t.join(c, (F.pmod("bucket", F.lit(groups)) == F.col("grp")) & (F.col("tj") == F.col("cj")) & within)
    return both.select("bucket", F.col("tj").alias("j"), "day", ((F.col("vt") / width_days + F.col("vc") / (50 / groups)) / 2).alias("v"))


def running_slabs(events: DataFrame) -> DataFrame:
    """Each user's running sums by event type, kept as state across triggers (arbitrary stateful processing)."""

    def add(key: tuple, batches: Iterator[pd.DataFrame], state: Any) -> Iterator[pd.DataFrame]:
        sums = dict(zip(*state.get)) if state.exists else {}
        for b in batches:
            for kind, v in b.groupby("event_type")["value"].sum().items():
                sums[kind] = sums.get(kind, 0.0) + float(v)
        state.update((list(sums), list(sums.values())))
        yield pd.DataFrame({"user_id": [key[0]] * len(sums), "event_type": list(sums), "v": list(sums.values())})

    from pyspark.sql.streaming.state import GroupStateTimeout

    return with_time(events).select("user_id", "event_type", "value").groupBy("user_id").applyInPandasWithState(
        add, "user_id long, event_type string, v double", "kinds array<string>, sums array<double>", "update", GroupStateTimeout.NoTimeout)


def run_available(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """All there is now, through to a table in the shared folder: for tests and backfills.

    "complete" keeps the last batch's table; "append" and "update" keep all rows that were sent: an updated key has a row for
    each update.
    """
    spark = df.sparkSession
    folder = f"{shared.shared_dir(spark)}/stream-{name}-{uuid.uuid4().hex}"

    def write(batch: DataFrame, batch_id: int) -> None:
        # A batch that is replayed writes over its own folder.
        batch.write.mode("overwrite").parquet(f"{folder}/rows/batch={0 if mode == 'complete' else batch_id}")

    spark.createDataFrame([], df.schema).write.parquet(f"{folder}/rows/batch=-1")
    q = df.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).option("recursiveFileLookup", True).parquet(f"{folder}/rows")


def _plain(x: Any) -> Any:
    return {"__array__": x.tolist()} if isinstance(x, np.ndarray) else x.tolist() if isinstance(x, np.generic) else x


def _array(x: dict) -> Any:
    return np.array(x["__array__"]) if "__array__" in x else x


def kept_fits(spark: SparkSession, folder: str) -> dict[int, dict]:
    """Fits of a folder by batch id."""
    try:
        rows = spark.read.schema("value string, batch long").option("pathGlobFilter", "*.txt").text(folder).collect()
    except AnalysisException:
        return {}
    return {r.batch: json.loads(r.value, object_hook=_array) for r in rows}


def warm_fits(events: DataFrame, refit: Callable[[DataFrame, dict | None], dict], checkpoint: str) -> list[dict]:
    """A fit after each micro-batch that goes on from the last factors.

    Each fit (numbers, lists and arrays) is written beside the checkpoint under its batch's id, so a stream that is started again goes on from the
    last one, and a batch that is replayed is skipped.
    """
    spark, folder = events.sparkSession, f"{checkpoint}/fits"

    def each(batch: DataFrame, batch_id: int) -> None:
        done = kept_fits(spark, folder)
        if batch_id not in done:
            last = done[max(done)] if done else None
            text = json.dumps(refit(batch, last), default=_plain)
            spark.createDataFrame([(text,)], "value string").coalesce(1).write.mode("overwrite").text(f"{folder}/batch={batch_id}")

    events.writeStream.foreachBatch(each).option("checkpointLocation", f"{checkpoint}/stream").trigger(availableNow=True).start().awaitTermination()
    done = kept_fits(spark, folder)
    return [done[n] for n in sorted(done)]
