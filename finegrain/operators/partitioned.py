"""The coupled method for a first mode whose factor is too large to broadcast.

The factor's rows live in a table, bucketed like the temporal view by blocks of members; a pass puts a block's rows and cells together
without a shuffle. The other factors, and the coarse first factor of the contemporaneous view (one row for each group), are broadcast as
usual. Only their sizes, and R x R sums, reach the driver.
"""

from __future__ import annotations

import atexit
import time
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from finegrain import shared
from finegrain.operators.groupings import Grouping
from finegrain.operators.kernels import Sums, ViewKernel, check_size, gram, others_gram
from finegrain.operators.views import View

_tables: list[tuple[SparkSession, str]] = []


def bucketed(df: DataFrame, blocks: int) -> DataFrame:
    """df (with a column ``block``) as a table bucketed and sorted by block, its files in the shared folder; dropped when the driver ends."""
    name = f"finegrain_{uuid.uuid4().hex}"
    folder = f"{shared.shared_dir(df.sparkSession)}/{name}"
    df.repartition(blocks, "block").write.bucketBy(blocks, "block").sortBy("block").format("parquet").option("path", folder).saveAsTable(name)
    shared.forget_later(df.sparkSession, folder)
    _tables.append((df.sparkSession, name))
    return df.sparkSession.table(name)


@atexit.register
def _clean() -> None:
    for spark, name in _tables:
        try:
            spark.sql(f"DROP TABLE IF EXISTS {name}")
        except Exception:  # the JVM may have ended first
            return


def block_of(column: str, blocks: int):
    return F.pmod(F.xxhash64(column), F.lit(blocks)).cast("int")


@dataclass
class WideFit:
    """rows: block, i, grp, weight, f (a row of the first factor for each member); j and k as matrices."""

    rows: DataFrame
    factors: dict[str, np.ndarray]
    losses: list[float]
    seconds: float

    def reconstruct(self, keys: DataFrame) -> DataFrame:
        """keys (i, j, k) with v: joined with the factor's rows by member."""
        check_size(self.factors)
        sent = keys.sparkSession.sparkContext.broadcast(self.factors)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            f = sent.value
            for batch in batches:
                a = _matrix(batch.column("f"), f["j"].shape[1])
                v = np.einsum("nr,nr,nr->n", a, f["j"][batch.column("j").to_numpy()], f["k"][batch.column("k").to_numpy()])
                yield pa.RecordBatch.from_arrays([batch.column("i"), batch.column("j"), batch.column("k"), pa.array(v)], names=["i", "j", "k", "v"])

        return keys.select("i", "j", "k").join(self.rows.select("i", "f"), "i").mapInArrow(run, "i long, j long, k long, v double")


def _matrix(column: pa.Array | pa.ChunkedArray, rank: int) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, rank)


class WideView:
    """The temporal view (grouped over time only) beside the first factor's rows."""

    def __init__(self, view: View, blocks: int):
        self.groups, self.absent, self.shape = view.groupings["k"], view.absent, view.shape
        cells = view.cells.where("v IS NOT NULL").select(block_of("i", blocks).alias("block"), "i", "j", "k", "v")
        self.cells, self.blocks = bucketed(cells, blocks), blocks
        self.squares = float(self.cells.agg(F.coalesce(F.sum(F.col("v") * F.col("v")), F.lit(0.0))).first()[0])

    def together(self, rows: DataFrame, run, schema: str) -> DataFrame:
        """run(cells, rows) for each block: two tables bucketed alike, so nothing is shuffled."""
        return self.cells.groupBy("block").cogroup(rows.groupBy("block")).applyInArrow(run, schema)

    def first_mode(self, rows: DataFrame, f: dict[str, np.ndarray], half_c: np.ndarray, residual: bool) -> DataFrame:
        """rows with g, the gradient of each member, and the block's data loss (on one row of each block)."""
        shared, rank = rows.sparkSession.sparkContext.broadcast((f, half_c)), f["j"].shape[1]
        g_others = gram(f["j"]) * gram(f["k"])

        def run(cells: pa.Table, own: pa.Table) -> pa.Table:
            f, half_c = shared.value
            i, a = own.column("i").to_numpy(), _matrix(own.column("f"), rank)
            order = np.argsort(i)
            at = order[np.searchsorted(i[order], cells.column("i").to_numpy())]
            others = f["j"][cells.column("j").to_numpy()] * f["k"][cells.column("k").to_numpy()]
            v = cells.column("v").to_numpy()
            e = np.einsum("nr,nr->n", others, a[at]) - v if residual else -v
            half = np.stack([np.bincount(at, e * others[:, r], len(i)) for r in range(rank)], 1)
            if residual:
                loss = float(e @ e)
            else:  # all absent cells are zeros: Gram matrices stand for the model's squares
                loss = float((gram(a) * g_others).sum()) + 2 * float((half * a).sum()) + float(v @ v)
                half = half + a @ g_others
            g = 2 * (half + own.column("weight").to_numpy()[:, None] * half_c[own.column("grp").to_numpy()])
            lost = np.zeros(len(i))
            lost[:1] = loss
            return own.append_column("g", pa.array(list(g), pa.list_(pa.float64()))).append_column("loss", pa.array(lost))

        return self.together(rows, run, "block int, i long, grp long, weight double, f array<double>, g array<double>, loss double")

    def squares_of(self, rows: DataFrame, f: dict[str, np.ndarray], column: str) -> float:
        """Squared model over the observed cells with a column of rows as the first factor."""
        shared, rank = rows.sparkSession.sparkContext.broadcast(f), f["j"].shape[1]

        def run(cells: pa.Table, own: pa.Table) -> pa.Table:
            f = shared.value
            i, a = own.column("i").to_numpy(), _matrix(own.column("a"), rank)
            order = np.argsort(i)
            at = order[np.searchsorted(i[order], cells.column("i").to_numpy())]
            p = np.einsum("nr,nr,nr->n", f["j"][cells.column("j").to_numpy()], f["k"][cells.column("k").to_numpy()], a[at])
            return pa.table({"s": [float(p @ p)]})

        own = rows.select("block", "i", F.col(column).alias("a"))
        return float(self.together(own, run, "s double").agg(F.sum("s")).first()[0] or 0.0)

    def other_mode(self, rows: DataFrame, f: dict[str, np.ndarray], mode: str, residual: bool) -> Sums:
        """Sums by an index of the second or the coarse third mode, of residuals or raw values."""
        shared, rank, n = rows.sparkSession.sparkContext.broadcast(f), f["j"].shape[1], len(f[mode])

        def run(cells: pa.Table, own: pa.Table) -> pa.Table:
            f = shared.value
            i, a = own.column("i").to_numpy(), _matrix(own.column("f"), rank)
            order = np.argsort(i)
            rows_ = a[order[np.searchsorted(i[order], cells.column("i").to_numpy())]]
            index, v = cells.column(mode).to_numpy(), cells.column("v").to_numpy()
            others = rows_ * f["k" if mode == "j" else "j"][cells.column("k" if mode == "j" else "j").to_numpy()]
            e = np.einsum("nr,nr->n", others, f[mode][index]) - v if residual else v
            sums = np.stack([np.bincount(index, e * others[:, r], n) for r in range(rank)], 1)
            hit = np.unique(index)
            return pa.table({"idx": np.append(hit, -1), "s": pa.array([*sums[hit], np.append(float(e @ e), np.zeros(rank - 1))], pa.list_(pa.float64()))})

        got = self.together(rows.select("block", "i", "f"), run, "idx long, s array<double>").groupBy("idx").agg(*(F.sum(F.col("s")[r]).alias(f"g{r}") for r in range(rank))).toArrow()
        index, table = got.column("idx").to_numpy(), np.stack([got.column(f"g{r}").to_numpy() for r in range(rank)], 1)
        out = Sums(np.zeros((n, rank)))
        out.rows[index[index >= 0]] = table[index >= 0]
        out.squares = float(table[index == -1][0, 0])
        return out


def row_sums(rows: DataFrame, column: str, n_groups: int, rank: int) -> tuple[np.ndarray, np.ndarray]:
    """The Gram matrix of a column of rows, and its weighted sums by group: partial sums in each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g, coarse = np.zeros((rank, rank)), np.zeros((n_groups, rank))
        for batch in batches:
            a = _matrix(batch.column(0), rank)
            g += a.T @ a
            np.add.at(coarse, batch.column("grp").to_numpy(), a * batch.column("weight").to_numpy()[:, None])
        every = np.vstack([g, coarse])
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(every))), pa.array(list(every), pa.list_(pa.float64()))], names=["n", "s"])

    got = rows.select(column, "grp", "weight").mapInArrow(run, "n long, s array<double>").groupBy("n").agg(*(F.sum(F.col("s")[r]).alias(f"s{r}") for r in range(rank))).orderBy("n").toArrow()
    every = np.stack([got.column(f"s{r}").to_numpy() for r in range(rank)], 1)
    return every[:rank], every[rank:]


def fit_coupled_wide(view_t: View, view_c_cells: DataFrame, areas: DataFrame, n_groups: int, rank: int, max_iter: int = 10, blocks: int = 64, start: dict[str, np.ndarray] | None = None, seed: int = 0, second: Grouping | None = None, absent_c: str | None = None) -> WideFit:
    """Block descent with a partitioned first factor.

    view_t: the temporal view. view_c_cells: cells (group, j, k, v) of the contemporaneous view. areas: member, grp, weight, one row for each
    member of the first mode. ``second`` groups the second mode of that view too. absent_c: what a cell without a row is there (as in
    view_t if not given). start may give j and k, and i as a matrix (tests); else members start from a hash of their index.
    """
    began = time.perf_counter()
    spark = view_t.cells.sparkSession
    n_i, n_j, n_k = view_t.shape
    w = view_t.groupings["k"]
    rng = np.random.default_rng(seed)
    start = start or {}
    f = {"j": start.get("j", rng.random((n_j, rank)) + 0.1), "k": start.get("k", rng.random((n_k, rank)) + 0.1)}
    first = areas.select(block_of("member", blocks).alias("block"), F.col("member").alias("i"), "grp", F.col("weight").cast("double").alias("weight"))
    if "i" in start:
        given = spark.createDataFrame([(n, [float(x) for x in row]) for n, row in enumerate(start["i"])], "i long, f array<double>")
        rows = bucketed(first.join(given, "i").select("block", "i", "grp", "weight", "f"), blocks)
    else:
        draws = F.array(*(F.pmod(F.xxhash64(F.col("i"), F.lit(seed), F.lit(r)), F.lit(1 << 20)) / F.lit(float(1 << 20)) + 0.1 for r in range(rank)))
        rows = bucketed(first.withColumn("f", draws), blocks)
    t = WideView(view_t, blocks)
    residual = view_t.absent == "missing"
    c = ViewKernel(View(view_c_cells, (n_groups, n_j, n_k), {"j": second}, absent_c or view_t.absent).placed(), {"i": "iu", "j": "j", "k": "k"})
    losses: list[float] = []
    for _ in range(max_iter):
        gram_a, coarse = row_sums(rows, "f", n_groups, rank)
        small = f | {"iu": coarse}
        tf = {"j": f["j"], "k": w.apply(f["k"])}
        # First mode.
        s = c.block(small, "i")
        moved = bucketed(t.first_mode(rows, tf, s.half, residual), blocks)
        gram_g, coarse_g = row_sums(moved, "g", n_groups, rank)
        loss = float(moved.agg(F.sum("loss")).first()[0]) + s.loss
        top = 0.5 * float(np.trace(gram_g))
        below = (t.squares_of(moved, tf, "g") if residual else float((gram_g * gram(tf["j"]) * gram(tf["k"])).sum())) + c.denominator(small, "i", coarse_g)
        step = top / below if below > 0 else 0.0
        rows = bucketed(moved.select("block", "i", "grp", "weight", F.zip_with("f", "g", lambda x, y: x - step * y).alias("f")), blocks)
        losses.append(loss - (top**2 / below if below > 0 else 0.0))
        # Second and third mode, with sums by their own (coarse) index.
        gram_a, coarse = row_sums(rows, "f", n_groups, rank)
        for mode in "jk":
            small, tf = f | {"iu": coarse}, {"j": f["j"], "k": w.apply(f["k"])}
            sums = t.other_mode(rows, tf, mode, residual)
            g_others = gram_a * gram(tf["k" if mode == "j" else "j"])
            if residual:
                half_t, loss_t = sums.rows, sums.squares
            else:
                half_t = tf[mode] @ g_others - sums.rows
                loss_t = float((gram(tf[mode]) * g_others).sum()) - 2 * float((tf[mode] * sums.rows).sum()) + t.squares
            s = c.block(small, mode)
            grouped = second if mode == "j" else None
            half = (half_t if mode == "j" else w.back(half_t)) + (grouped.back(s.half) if grouped else s.half)
            gradient = 2 * half
            direction = gradient if mode == "j" else w.apply(gradient)
            if residual:
                below = t.squares_of(rows, tf | {mode: direction}, "f")
            else:
                below = float((gram(direction) * g_others).sum())
            below += c.denominator(small, mode, grouped.apply(gradient) if grouped else gradient)
            top = 0.5 * float((gradient**2).sum())
            f = f | {mode: f[mode] - (top / below if below > 0 else 0.0) * gradient}
            losses.append(loss_t + s.loss - (top**2 / below if below > 0 else 0.0))
    return WideFit(rows, f, losses, time.perf_counter() - began)


__all__ = ["WideFit", "WideView", "fit_coupled_wide", "others_gram"]
