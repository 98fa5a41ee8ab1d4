"""The variant for unknown groupings: coarse factors of their own, tied only by their column sums over time."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import functions as F

from finegrain.operators.coupled import CP_ITERATIONS, ITERATIONS, Fit, SumPenalty, descend, third_factor
from finegrain.operators.cpd import als
from finegrain.operators.groupings import Grouping, chunk
from finegrain.operators.kernels import ViewKernel
from finegrain.operators.views import View

MU = 100.0


def chunk_sums(c: np.ndarray, periods: int) -> np.ndarray:
    """Sums of consecutive rows, ragged where the number of ticks doesn't divide."""
    return chunk(len(c), periods).apply(c)


def column_sum_penalty(c: np.ndarray, coarse: np.ndarray, mu: float = MU) -> float:
    return SumPenalty(mu, np.ones(len(c))).value({"k": c, "kt": coarse})


def relative_mu(view_t: View, mu: float = MU) -> float:
    """mu times the mean squared value, so that it means the same on any scale of the data."""
    return mu * float(view_t.cells.agg(F.avg(F.col("v") * F.col("v"))).first()[0] or 1.0)


def _without_groupings(view: View) -> View:
    return View(view.cells, view.coarse_shape, {}, view.absent, view.holes, view.weight)


def init_blind(view_t: View, view_c: View, rank: int, cp_iterations: int = CP_ITERATIONS, seed: int = 0) -> tuple[dict[str, np.ndarray], int]:
    """CPD of the contemporaneous view gives the coarse first factor, B and C; chunk sums of C the coarse time factor; A by least squares."""
    cp = als(view_c, rank, cp_iterations, seed=seed)
    factors = {"it": cp.factors["i"], "j": cp.factors["j"], "k": cp.factors["k"], "kt": chunk_sums(cp.factors["k"], view_t.shape[2])}
    kernel = ViewKernel(view_t, {"i": "i", "j": "j", "k": "kt"})
    a = third_factor(kernel, factors | {"i": np.zeros((view_t.shape[0], rank))}, "i")
    return factors | {"i": a}, cp.passes + kernel.passes


def blind_kernels(view_t: View, view_c: View, known: dict[str, Grouping] | None = None) -> list[ViewKernel]:
    """Kernels whose coarse modes have factors of their own, or the fine factor with its grouping where that one is known."""
    known = known or {}
    t = ViewKernel(View(view_t.cells, view_t.shape[:2] + (view_c.shape[2],), {"k": known["W"]}, view_t.absent, view_t.holes, view_t.weight)) if "W" in known else ViewKernel(view_t, {"i": "i", "j": "j", "k": "kt"})
    c = ViewKernel(View(view_c.cells, (view_t.shape[0],) + view_c.shape[1:], {"i": known["U"]}, view_c.absent, view_c.holes, view_c.weight)) if "U" in known else ViewKernel(view_c, {"i": "it", "j": "j", "k": "k"})
    return [t, c]


def fit_blind(view_t: View, view_c: View, rank: int, mu: float | str = MU, max_iter: int = ITERATIONS, cp_iterations: int = CP_ITERATIONS, seed: int = 0, known: dict[str, Grouping] | None = None, tick_weights: np.ndarray | None = None, chunk_scale: float = 1.0, tol: float | None = None) -> Fit:
    """Fine factors i, j, k (and the coarse it, kt) from views whose groupings aren't used.

    The views must aggregate one mode each: time, and the first mode. known={"W": ...} or {"U": ...} ties the coarse factor
    whose grouping is known after all, and drops its block. tick_weights counts a tick as often as overlapping
    periods take it; chunk_scale is the period's length for averaging views. mu="relative" scales with the data.
    """
    began = time.perf_counter()
    if view_c.groupings.get("j") is not None or view_t.groupings.get("j") is not None:
        raise ValueError("unknown groupings can be handled for views that aggregate one mode each")
    known = known or {}
    t, c = _without_groupings(view_t).placed(), _without_groupings(view_c).placed()
    factors, passes = init_blind(t, c, rank, cp_iterations, seed)
    strength = relative_mu(t) if mu == "relative" else float(mu)
    penalty = None
    order = ["i", "it", "j", "k", "kt"]
    if "W" in known:
        order.remove("kt")
    elif strength > 0:
        penalty = SumPenalty(strength, np.ones(c.shape[2]) if tick_weights is None else tick_weights, chunk_scale)
    if "U" in known:
        order.remove("it")
    kernels = blind_kernels(t, c, known)
    # Columns aren't rebalanced: their scale between the views is what the penalty pins down.
    factors, trace = descend(kernels, factors, tuple(order), max_iter, tol, penalty, rebalance=False)
    return Fit(factors, trace, passes + sum(k.passes for k in kernels), "contemporaneous", time.perf_counter() - began)


def blind_loss(factors: dict[str, np.ndarray], view_t: View, view_c: View, mu: float = MU) -> float:
    kernels = blind_kernels(_without_groupings(view_t), _without_groupings(view_c))
    return sum(k.loss(factors) for k in kernels) + SumPenalty(mu, np.ones(len(factors["k"]))).value(factors)
