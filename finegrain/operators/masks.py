"""Patterns of missing cells, by integer hashes of the indexes: the same on each machine, and in SQL."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FACTORS = {"i": 7919, "j": 104729, "k": 1299709}


def _hash(modes: tuple[str, ...], seed: int) -> Column:
    return F.pmod(reduce(lambda a, b: a + b, (FACTORS[m] * F.col(m) for m in modes)) + seed, F.lit(1000))


def mask_random(cells: DataFrame, fraction: float, seed: int = 0) -> DataFrame:
    """cells without about ``fraction`` of them, each by itself."""
    return cells.where(_hash(("i", "j", "k"), seed) >= round(1000 * fraction))


def mask_fiber(cells: DataFrame, mode: str, fraction: float, seed: int = 0) -> DataFrame:
    """cells without about ``fraction`` of the fibres that run along ``mode``."""
    return cells.where(_hash(tuple(m for m in "ijk" if m != mode), seed) >= round(1000 * fraction))


def mask_regular(cells: DataFrame, mode: str, step: int, offset: int = 0) -> DataFrame:
    """Every step-th index of a mode only."""
    return cells.where(F.pmod(F.col(mode) - offset, F.lit(step)) == 0)


def mask_structural(cells: DataFrame, facts: DataFrame, modes: tuple[str, ...]) -> DataFrame:
    """cells whose indexes of ``modes`` occur together in facts (as a store that never had an item)."""
    return cells.join(facts.select(*modes).distinct(), list(modes), "left_semi")


def starve_slab(cells: DataFrame, k: int, keep: int) -> DataFrame:
    """cells with only the first ``keep`` of slab k, in the order of (i, j)."""
    from pyspark.sql import Window

    slab = cells.where(F.col("k") == k).withColumn("_n", F.row_number().over(Window.orderBy("i", "j"))).where(F.col("_n") <= keep).drop("_n")
    return cells.where(F.col("k") != k).unionByName(slab)
