"""Planted cubes: low rank by construction, from integer arithmetic that SQL can repeat."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SIZE = (25, 25, 357)
SCALE = 100.0


def planted_factors(rank: int = 4, size: tuple[int, int, int] = SIZE, signed: bool = False) -> dict[str, np.ndarray]:
    n_i, n_j, n_k = size
    i, j, k = (np.arange(n)[:, None] for n in (n_i, n_j, n_k))
    r = np.arange(rank)[None, :]
    return {
        "i": ((37 * i + 53 * (r + 1) + i * i * (r + 2)) % 101) / 100 + 0.05,
        "j": ((61 * j + 29 * (r + 1) + j * j * (r + 2)) % 101) / 100 + 0.05,
        "k": (0.0 if signed else 1.0) + 0.9 * np.sin(2 * np.pi * (k * (r + 1) / 52 + ((13 * k % 7) / 7) * (r % 2) + 0.17 * r)),
    }


def planted_value(rank: int = 4, signed: bool = False) -> Column:
    """The value of cell (i, j, k) as an expression: made where it is needed, in generated code."""
    i, j, k = F.col("i"), F.col("j"), F.col("k")
    total = F.lit(0.0)
    for r in range(rank):
        a = F.pmod(37 * i + 53 * (r + 1) + i * i * (r + 2), F.lit(101)) / F.lit(100.0) + 0.05
        b = F.pmod(61 * j + 29 * (r + 1) + j * j * (r + 2), F.lit(101)) / F.lit(100.0) + 0.05
        turn = k * (r + 1) / F.lit(52.0) + F.pmod(13 * k, F.lit(7)) / F.lit(7.0) * (r % 2) + 0.17 * r
        total = total + a * b * ((0.0 if signed else 1.0) + 0.9 * F.sin(2 * np.pi * turn))
    return SCALE * total


def grid(spark: SparkSession, size: tuple[int, int, int] = SIZE) -> DataFrame:
    """All cells (i, j, k) of a cube, from one range: no join."""
    n_i, n_j, n_k = size
    at = spark.range(n_i * n_j * n_k)
    return at.select(F.floor(F.col("id") / (n_j * n_k)).alias("i"), F.pmod(F.floor(F.col("id") / n_k), F.lit(n_j)).alias("j"), F.pmod("id", F.lit(n_k)).alias("k"))


def noise(percent: int, seed: int = 0) -> Column:
    """A factor 1 + percent/100 * u with u in [-1, 1) from an integer hash of the cell."""
    mixed = F.pmod(F.pmod((F.col("i") * 7919 + F.col("j") * 104729 + F.col("k") * 1299709 + seed * 15485863) * 48271, F.lit(2147483647)) * 16807, F.lit(2147483647))
    return 1 + percent / 100.0 * (F.pmod(mixed, F.lit(20001)) / F.lit(10000.5) - 1)


def planted_cube(spark: SparkSession, rank: int = 4, size: tuple[int, int, int] = SIZE, signed: bool = False, noise_percent: int = 0) -> DataFrame:
    cells = grid(spark, size).withColumn("v", planted_value(rank, signed))
    return cells.withColumn("v", F.col("v") * noise(noise_percent)) if noise_percent else cells


class PlantedCubeSource(DataSource):
    """``spark.read.format("planted_cube").option("rank", 4).option("size", "25,25,357").load()``: one partition for each range of ticks.

    Or ``.option("factors", ...)``: three lists of rows (JSON), taken as they are in place of the planted ones.
    """

    @classmethod
    def name(cls) -> str:
        return "planted_cube"

    def schema(self) -> str:
        return "i long, j long, k long, v double"

    def reader(self, schema) -> DataSourceReader:
        size = tuple(int(x) for x in self.options.get("size", "25,25,357").split(","))
        return _Reader(int(self.options.get("rank", 4)), size, int(self.options.get("ticks", 60)), self.options.get("factors"))


class _Reader(DataSourceReader):
    def __init__(self, rank: int, size: tuple[int, int, int], ticks: int, factors: str | None = None):
        self.rank, self.size, self.ticks, self.factors = rank, size, ticks, factors

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(0, self.size[2], self.ticks)]

    def read(self, partition: InputPartition) -> Iterator:
        import pyarrow as pa

        given = self.factors is not None
        f = dict(zip("ijk", map(np.array, json.loads(self.factors)))) if given else planted_factors(self.rank, self.size)
        k = np.arange(partition.value, min(partition.value + self.ticks, self.size[2]))
        v = (1.0 if given else SCALE) * np.einsum("ir,jr,kr->ijk", f["i"], f["j"], f["k"][k])
        at = np.indices(v.shape).reshape(3, -1)
        yield pa.RecordBatch.from_arrays([pa.array(at[0]), pa.array(at[1]), pa.array(k[at[2]]), pa.array(v.ravel())], names=["i", "j", "k", "v"])
