"""Accuracy and cost measures."""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from finegrain.operators.held import HeldCells
from finegrain.operators.kernels import cell_pass, gram
from finegrain.operators.views import View, mode_products


def nde_columns(truth: Column, estimate: Column) -> tuple[Column, Column]:
    """The two sums whose quotient is the error: partial sums on every task."""
    return F.sum((truth - estimate) ** 2), F.sum(truth**2)


def nde(truth: DataFrame, estimate: DataFrame, over: str = "observed") -> DataFrame:
    """One row: nde, n_cells. |X - X^|^2 / |X|^2 over the cells of the true cube ("observed"), or over the cells of either ("all"),
    where a cell without a row is zero. Estimates that are null or absent count as zero.

    Repeated keys are errors of the caller; both sides need one row a cell.
    """
    keys = ["i", "j", "k"]
    t, e = truth.select(*keys, F.col("v").alias("_x")), estimate.select(*keys, F.col("v").alias("_e"))
    both = t.where("_x IS NOT NULL").join(e, keys, "left" if over == "observed" else "full_outer")
    top, below = nde_columns(F.coalesce("_x", F.lit(0.0)), F.coalesce("_e", F.lit(0.0)))
    return both.agg(top.alias("_top"), below.alias("_below"), F.count("*").alias("n_cells")).select((F.col("_top") / F.col("_below")).alias("nde"), "n_cells")


def nde_value(truth: DataFrame, estimate: DataFrame, over: str = "observed") -> float:
    return float(nde(truth, estimate, over).first()[0])


def nde_pieces(truth: HeldCells, pieces: Iterable[tuple[np.ndarray, np.ndarray, np.ndarray | None]], rest: bool = True) -> float:
    """The error of an estimate in pieces that don't overlap (first and second indexes, and their series); it is zero where none is.

    Where several tasks share an estimate, their errors add up to the whole one: a piece of another task has no series, and one task counts the rest.
    """
    left, off = truth.seen.copy(), 0.0
    for i, j, series in pieces:
        at = np.ix_(i, j)
        left[at] = False
        if series is not None:
            off += float((((truth.values[at] - series) * truth.seen[at]) ** 2).sum())
    return (off + (float((truth.values[left] ** 2).sum()) if rest else 0.0)) / truth.squares


def nde_gram(truth: DataFrame, factors: dict[str, np.ndarray]) -> float:
    """The error over all cells (absent: zero) without making the estimate: one pass over the true cells, Gram matrices for
    the rest. Loses digits where the error is below 1e-12 or so."""
    f = {m: factors[m] for m in "ijk"}
    s = cell_pass(truth.where("v IS NOT NULL"), f, "i", "raw")
    whole = float((gram(f["i"]) * gram(f["j"]) * gram(f["k"])).sum())
    return max(0.0, s.squares - 2 * float((f["i"] * s.rows).sum()) + whole) / s.squares


def nde_model(truth: DataFrame, factors: dict[str, np.ndarray]) -> float:
    """The error of a model over the observed cells of the true cube: one pass, nothing joined."""
    f = {m: factors[m] for m in "ijk"}
    if isinstance(truth, HeldCells):
        return cell_pass(truth, f, "i").squares / truth.squares
    observed = truth.where("v IS NOT NULL")
    s = cell_pass(observed, f, "i")
    return s.squares / float(observed.agg(F.sum(F.col("v") ** 2)).first()[0])


def leaderboard(scores: DataFrame) -> DataFrame:
    """Scores (workload, level, method, rank, nde) with the place of each method's best rank, and marks for the best two."""
    best = scores.groupBy("workload", "level", "method").agg(F.min(F.struct("nde", "rank")).alias("b")).select("workload", "level", "method", "b.nde", "b.rank")
    place = F.dense_rank().over(Window.partitionBy("workload", "level").orderBy("nde"))
    return best.withColumn("place", place).withColumn("mark", F.when(F.col("place") == 1, "best").when(F.col("place") == 2, "second"))


def improvement(scores: DataFrame, ours: tuple[str, ...] = ("coupled_cp", "blind_cp"), oracle: str = "cp_oracle") -> DataFrame:
    """workload, level, ratio of the best baseline's error to our method's (coupled_cp), and the relative reduction."""
    by = scores.groupBy("workload", "level").agg(
        F.min(F.when(~F.col("method").isin(*ours, oracle), F.col("nde"))).alias("baseline"), F.min(F.when(F.col("method") == ours[0], F.col("nde"))).alias("ours"))
    return by.withColumn("ratio", F.col("baseline") / F.col("ours")).withColumn("reduction", 1 - F.col("ours") / F.col("baseline"))


def oracle_gap(scores: DataFrame, method: str = "coupled_cp", oracle: str = "cp_oracle") -> DataFrame:
    """How far a method is from the decomposition of the true cube of the same rank."""
    a = scores.where(F.col("method") == method).select("workload", "level", "rank", F.col("nde").alias("nde"))
    b = scores.where(F.col("method") == oracle).select("workload", "level", "rank", F.col("nde").alias("floor"))
    return a.join(b, ["workload", "level", "rank"]).withColumn("gap", F.col("nde") - F.col("floor"))


def rank_plateau(scores: DataFrame, tolerance: float = 0.1) -> DataFrame:
    """Ranks whose error is within (1 + tolerance) of the best rank's, for each workload, level and method."""
    best = F.min("nde").over(Window.partitionBy("workload", "level", "method"))
    return scores.withColumn("usable", F.col("nde") <= best * (1 + tolerance))


def measurement_fraction(view: View) -> float:
    """Cells of the view as a share of the cells of the cube."""
    return float(np.prod(view.coarse_shape) / np.prod(view.shape))


def consistency(estimate: DataFrame, view: View) -> DataFrame:
    """One row: the squared residual of the estimate's own view against the view, relative to the view, and the largest one."""
    own = mode_products(estimate, view.groupings).withColumnRenamed("v", "_e")
    both = view.cells.join(own, ["i", "j", "k"], "left")
    gap = F.col("v") - F.coalesce("_e", F.lit(0.0))
    return both.agg((F.sum(gap**2) / F.sum(F.col("v") ** 2)).alias("relative"), F.max(F.abs(gap)).alias("largest"))


def worst_cells(truth: DataFrame, estimate: DataFrame, n: int = 20) -> DataFrame:
    """The n cells with the largest absolute error: a bounded heap on every task."""
    both = truth.join(estimate.withColumnRenamed("v", "estimate"), ["i", "j", "k"])
    return both.withColumn("error", F.abs(F.col("v") - F.col("estimate"))).orderBy(F.desc("error"), "i", "j", "k").limit(n)
