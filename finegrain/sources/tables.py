"""Scans and sinks."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from finegrain import shared

TABLES = (
    "region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events",
    "documents", "embeddings", "pages", "benchmark", "labels", "conversations",
)


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def register(spark: SparkSession, sf_dir: str, tables: tuple[str, ...] = TABLES) -> None:
    """Temporary views of the tables, for SQL."""
    for t in tables:
        load(spark, sf_dir, t).createOrReplaceTempView(t)


def save_cells(cells: DataFrame, path: str, ticks_per_block: int = 64) -> None:
    """Cells by block of ticks (pruned by time filters), sorted by i within a file (skipped by its statistics)."""
    blocked = cells.withColumn("kb", F.floor(F.col("k") / ticks_per_block))
    blocked.repartition("kb", F.pmod(F.xxhash64("i", "j"), F.lit(16))).sortWithinPartitions("kb", "i", "j").write.partitionBy("kb").mode("overwrite").parquet(path)


def load_cells(spark: SparkSession, path: str, ticks: tuple[int, int] | None = None, ticks_per_block: int = 64) -> DataFrame:
    cells = spark.read.parquet(path)
    if ticks:
        low, high = ticks
        cells = cells.where(F.col("kb").between(low // ticks_per_block, high // ticks_per_block) & F.col("k").between(low, high))
    return cells.drop("kb")


def bucket_cells(cells: DataFrame, table: str, mode: str = "i", buckets: int = 64) -> DataFrame:
    """Cells as a table bucketed by one mode, its files in the shared folder: joins with a factor bucketed alike need no shuffle."""
    folder = f"{shared.shared_dir(cells.sparkSession)}/{table}"
    cells.write.bucketBy(buckets, mode).sortBy(mode).mode("overwrite").format("parquet").option("path", folder).saveAsTable(table)
    return cells.sparkSession.table(table)


def factor_frame(spark: SparkSession, factor: np.ndarray) -> DataFrame:
    """A factor matrix as idx, f."""
    rows = [(i, [float(x) for x in row]) for i, row in enumerate(factor)]
    return spark.createDataFrame(rows, "idx long, f array<double>")


def save_fit(spark: SparkSession, factors: dict[str, np.ndarray], path: str, meta: dict | None = None) -> None:
    """Factors (one row each) and a JSON description; a fit can go on from them (``init="given"``)."""
    rows = [(mode, i, [float(x) for x in row]) for mode, m in factors.items() for i, row in enumerate(m)]
    spark.createDataFrame(rows, "mode string, idx long, f array<double>").write.mode("overwrite").partitionBy("mode").parquet(f"{path}/factors")
    spark.createDataFrame([(json.dumps(meta or {}),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")


def load_fit(spark: SparkSession, path: str) -> tuple[dict[str, np.ndarray], dict]:
    factors: dict[str, list] = {}
    for mode, _, f in spark.read.parquet(f"{path}/factors").select("mode", "idx", "f").orderBy("mode", "idx").collect():
        factors.setdefault(mode, []).append(f)
    return {m: np.array(f) for m, f in factors.items()}, json.loads(spark.read.text(f"{path}/meta").first()[0])


def save_scores(scores: DataFrame, path: str, fmt: str = "csv") -> None:
    """Score tables as csv, json, orc or parquet."""
    writer = scores.write.mode("overwrite").format(fmt)
    (writer.option("header", True) if fmt == "csv" else writer).save(path)
