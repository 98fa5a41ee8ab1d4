"""When the fine cube is determined: rank bound, observation per tick, and equality of factors up to order and scale."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

RANKS = (10, 25, 40)


def rank_bound(n_i: int, n_j: int, iu: int, jv: int, kw: int) -> int:
    """The largest rank for which recovery is guaranteed with a complete temporal view."""
    return min(n_i * n_j, n_i * kw, n_j * kw, 16 * iu * jv) // 16


def rank_bound_column(n_i: Column, n_j: Column, iu: Column, jv: Column, kw: Column) -> Column:
    return F.floor(F.least(n_i * n_j, n_i * kw, n_j * kw, 16 * iu * jv) / 16).cast("long")


def ranks_for(shape: tuple[int, int, int], coarse_c: tuple[int, int, int], periods: int, ranks: tuple[int, ...] = RANKS, margin: float = 1.0) -> list[int]:
    """The ranks within the bound (times a margin below 1, where rank near the bound fits noise), or the bound itself."""
    most = int(margin * rank_bound(shape[0], shape[1], coarse_c[0], coarse_c[1], periods))
    return [r for r in ranks if r <= most] or [max(most, 1)]


def slab_check(cells: DataFrame, ticks: int, rank: int) -> DataFrame:
    """k, observed, enough for each tick of a contemporaneous view, those without a row too."""
    counts = cells.where("v IS NOT NULL").groupBy("k").agg(F.count("*").alias("observed"))
    every = cells.sparkSession.range(ticks).select(F.col("id").alias("k"))
    return every.join(counts, "k", "left").select("k", F.coalesce("observed", F.lit(0)).alias("observed")).withColumn("enough", F.col("observed") >= rank)


def slab_systems(cells: DataFrame, coarse: dict[str, np.ndarray]) -> Iterator[tuple[int, np.ndarray, np.ndarray, int]]:
    """(k, normal matrix, right side, cells) of each tick's observed cells, for the rows of the coarse first and second factor.

    Sums are made per batch and tick, then added: a tick with very many cells is no single task.
    """
    spark = cells.sparkSession
    shared = spark.sparkContext.broadcast({m: coarse[m] for m in "ij"})
    rank = coarse["i"].shape[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = shared.value
        for batch in batches:
            i, j, k, v = (batch.column(c).to_numpy() for c in "ijkv")
            z = f["i"][i] * f["j"][j]
            ks, inverse = np.unique(k, return_inverse=True)
            out = np.zeros((len(ks), rank * rank + rank + 1))
            full = np.concatenate([np.einsum("nr,ns->nrs", z, z).reshape(len(z), -1), z * v[:, None], np.ones((len(z), 1))], 1)
            np.add.at(out, inverse, full)
            yield pa.RecordBatch.from_arrays([pa.array(ks), pa.array(list(out), pa.list_(pa.float64()))], names=["k", "s"])

    parts = cells.select("i", "j", "k", "v").where("v IS NOT NULL").mapInArrow(run, "k long, s array<double>")
    width = rank * rank + rank + 1
    summed = parts.groupBy("k").agg(*(F.sum(F.col("s")[n]).alias(f"s{n}") for n in range(width)))
    for row in summed.toLocalIterator():
        s = np.array(row[1:])
        yield int(row[0]), s[: rank * rank].reshape(rank, rank), s[rank * rank : -1], int(s[-1])


def slab_rank(cells: DataFrame, coarse: dict[str, np.ndarray]) -> dict[int, int]:
    """Rank of the observed rows of the coarse factors' Khatri-Rao product, by tick."""
    return {k: int(np.linalg.matrix_rank(g)) for k, g, _, _ in slab_systems(cells, coarse)}


def match_factors(one: dict[str, np.ndarray], two: dict[str, np.ndarray]) -> tuple[float, list[int]]:
    """How alike two models are up to order and scale: the mean over columns of the product of absolute cosines, by the
    best greedy assignment, and the order of two's columns."""
    unit = lambda f: f / np.maximum(np.linalg.norm(f, axis=0), 1e-300)
    alike = np.prod([np.abs(unit(one[m]).T @ unit(two[m])) for m in one], axis=0)
    order, left, scores = [-1] * len(alike), alike.copy(), []
    for _ in range(min(alike.shape)):
        a, b = np.unravel_index(int(left.argmax()), left.shape)
        scores.append(alike[a, b])
        order[a] = int(b)
        left[a, :] = left[:, b] = -1
    return float(np.mean(scores)), order


def bounds_frame(spark: SparkSession, sizes: list[tuple[str, int, int, int, int, int]]) -> DataFrame:
    """name, sizes and the bound of each configuration."""
    df = spark.createDataFrame(sizes, "name string, n_i long, n_j long, iu long, jv long, kw long")
    return df.withColumn("bound", rank_bound_column(*(F.col(c) for c in ("n_i", "n_j", "iu", "jv", "kw"))))
