"""The coupled method: one set of factors for several coarse views with known groupings.

Blocks are updated in turn along their negative gradient with the step that is best on that line. For a block with
gradient G, half of ``<G, G>`` is the inner product of the residual with the model of G, with or without the regulariser;
so a step needs the gradient and one squared norm, and the loss after it is known without another pass.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from finegrain.operators.cpd import als, balanced, random_factors
from finegrain.operators.identifiability import rank_bound
from finegrain.operators.kernels import ViewKernel, blocks, denominators, others_gram, solve_rows
from finegrain.operators.views import View

CP_ITERATIONS, ITERATIONS = 10, 10


@dataclass
class Fit:
    """Factors, the trace of the descent (a row for each block update) and what it cost."""

    factors: dict[str, np.ndarray]
    trace: list[dict] = field(default_factory=list)
    passes: int = 0
    start: str = ""
    seconds: float = 0.0

    @property
    def rank(self) -> int:
        return next(iter(self.factors.values())).shape[1]

    @property
    def monotone(self) -> bool:
        """Whether no block update has raised the loss of the views that have the block."""
        return all(t["loss"] <= t["before"] * (1 + 1e-9) + 1e-9 for t in self.trace if "before" in t)

    @property
    def losses(self) -> list[float]:
        return [t["loss"] for t in self.trace]

    def trace_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(t["iter"], t["block"], t["loss"], t["reg"], t["step"], t["grad_sq"], t["cells"]) for t in self.trace]
        return spark.createDataFrame(rows, "iter int, block string, loss double, reg double, step double, grad_sq double, cells_read long")


class SumPenalty:
    """mu * |w'C - scale * 1'C~|^2: the columns of the fine and the coarse time factor add up alike."""

    def __init__(self, mu: float, ticks: np.ndarray, scale: float = 1.0, fine: str = "k", coarse: str = "kt"):
        self.mu, self.ticks, self.scale, self.fine, self.coarse = mu, ticks, scale, fine, coarse

    def gap(self, f: dict[str, np.ndarray]) -> np.ndarray:
        return self.ticks @ f[self.fine] - self.scale * f[self.coarse].sum(0)

    def value(self, f: dict[str, np.ndarray]) -> float:
        return self.mu * float((self.gap(f) ** 2).sum())

    def half_gradient(self, f: dict[str, np.ndarray], name: str) -> np.ndarray | float:
        if name == self.fine:
            return self.mu * np.outer(self.ticks, self.gap(f))
        if name == self.coarse:
            return -self.mu * self.scale * np.tile(self.gap(f), (len(f[name]), 1))
        return 0.0

    def squares(self, name: str, direction: np.ndarray) -> float:
        if name == self.fine:
            return self.mu * float(((self.ticks @ direction) ** 2).sum())
        if name == self.coarse:
            return self.mu * self.scale**2 * float((direction.sum(0) ** 2).sum())
        return 0.0


def half_gradient(kernels: list[ViewKernel], factors: dict[str, np.ndarray], name: str, penalty: SumPenalty | None = None) -> tuple[np.ndarray, float, int]:
    """Half the gradient with respect to a factor, the data loss of the views that have it, and cells read.

    Each view's sums come in coarse rows; groupings spread them to members afterwards, which moves the fewer numbers.
    """
    half, loss, cells = np.zeros_like(factors[name]), 0.0, 0
    members = [(k, mode) for k in kernels if (mode := k.mode_of(name)) is not None]
    for (kernel, mode), s in zip(members, blocks(members, factors), strict=True):
        g = kernel.view.groupings.get(mode)
        half += kernel.view.weight * (g.back(s.half) if g else s.half)
        loss += kernel.view.weight * s.loss
        cells += s.cells
    if penalty:
        half = half + penalty.half_gradient(factors, name)
    return half, loss, cells


def model_squares(kernels: list[ViewKernel], factors: dict[str, np.ndarray], name: str, direction: np.ndarray, penalty: SumPenalty | None = None) -> float:
    """The views' squared norm of the model with ``direction`` in place of a factor, and the penalty's."""
    grouped = lambda k, mode: g.apply(direction) if (g := k.view.groupings.get(mode)) else direction
    members = [(k, mode, grouped(k, mode)) for k in kernels if (mode := k.mode_of(name)) is not None]
    out = sum(k.view.weight * x for (k, _, _), x in zip(members, denominators(members, factors), strict=True))
    return out + (penalty.squares(name, direction) if penalty else 0.0)


def exact_step(kernels: list[ViewKernel], factors: dict[str, np.ndarray], name: str, gradient: np.ndarray, penalty: SumPenalty | None = None) -> tuple[float, float, float]:
    """The best step along the negative gradient, its numerator and denominator."""
    top = 0.5 * float((gradient**2).sum())
    below = model_squares(kernels, factors, name, gradient, penalty)
    return (top / below if below > 0 else 0.0), top, below


def descend(kernels: list[ViewKernel], factors: dict[str, np.ndarray], order: tuple[str, ...], iterations: int, tol: float | None = None, penalty: SumPenalty | None = None, nonneg: bool = False, rebalance: bool = True) -> tuple[dict[str, np.ndarray], list[dict]]:
    """Cyclic block descent. The loss of a trace row is that of the views with the block, after its update."""
    trace: list[dict] = []
    before = None
    for it in range(iterations):
        for name in order:
            half, loss, cells = half_gradient(kernels, factors, name, penalty)
            gradient = 2 * half
            step, top, below = exact_step(kernels, factors, name, gradient, penalty)
            new = factors[name] - step * gradient
            whole = loss + (penalty.value(factors) if penalty else 0.0)
            after = whole - (top**2 / below if below > 0 else 0.0)
            if nonneg:
                new, after, step = _projected(kernels, factors, name, half, step, loss)
            factors = factors | {name: new}
            trace.append({"iter": it, "block": name, "before": whole, "loss": after, "reg": penalty.value(factors) if penalty else 0.0, "step": step, "grad_sq": 2 * top, "cells": cells})
        if rebalance:
            factors = balanced(factors)
        if tol is not None and before is not None and before - after <= tol * max(before, 1e-300):
            break
        before = after
    return factors, trace


def _projected(kernels, factors, name, half, step, loss) -> tuple[np.ndarray, float, float]:
    """A projected step; the line's best step may overshoot after the projection, so it is halved while the loss grows.

    The loss after a move is the loss, twice the move's product with half the gradient, and the squared norm of the move's model: nothing else is read.
    """
    for _ in range(20):
        new = np.maximum(factors[name] - 2 * step * half, 0)
        move = new - factors[name]
        after = loss + 2 * float((half * move).sum()) + model_squares(kernels, factors, name, move)
        if after <= loss * (1 + 1e-12):
            return new, max(after, 0.0), step
        step /= 2
    return factors[name], loss, 0.0


def coupled_loss(factors: dict[str, np.ndarray], views: list[View]) -> float:
    """The weighted squared residual of all views."""
    return sum(v.weight * ViewKernel(v).loss(factors) for v in views)


def choose_branch(view_t: View, view_c: View, init: str) -> str:
    """Which view to decompose first: "temporal" or "contemporaneous".

    auto: the contemporaneous one if it keeps the second mode whole and has more ticks than first-mode members.
    bound: the one whose own recovery bound is larger.
    """
    n_i, _, n_k = view_t.shape
    if init == "bound":
        iu, jv, _ = view_c.coarse_shape
        kw = view_t.coarse_shape[2]
        own = rank_bound(view_t.shape[0], view_t.shape[1], iu, jv, kw)
        mirrored = min(iu * jv, iu * n_k, jv * n_k, 16 * n_i * kw) // 16  # the same theorem with the views exchanged
        return "temporal" if own >= mirrored else "contemporaneous"
    if init == "auto":
        return "contemporaneous" if view_c.groupings.get("j") is None and n_k > n_i else "temporal"
    return init


def third_factor(kernel: ViewKernel, factors: dict[str, np.ndarray], mode: str) -> np.ndarray:
    """The factor of one (ungrouped) mode by least squares on a view, given the others; missing cells count as zeros."""
    coarse = kernel.coarse(factors)
    return solve_rows(others_gram(coarse, mode), kernel.raw(factors, mode))


def init_coupled(view_t: View, view_c: View, rank: int, init: str = "auto", cp_iterations: int = CP_ITERATIONS, seed: int = 0, nonneg: bool = False) -> tuple[dict[str, np.ndarray], str, int]:
    """Starting factors, the branch taken, and passes over cells."""
    if init == "random":
        return random_factors(view_t.shape, rank, seed, view_t.modes), "random", 0
    if len(view_t.shape) != 3:
        return _init_many_modes(view_t, view_c, rank, cp_iterations, seed, nonneg)
    branch = choose_branch(view_t, view_c, init)
    if branch == "contemporaneous":
        if view_c.groupings.get("j") is not None:
            raise ValueError("the contemporaneous start needs the second mode ungrouped")
        cp, other, mode = als(view_c, rank, cp_iterations, seed=seed, nonneg=nonneg), ViewKernel(view_t), "i"
    elif branch == "temporal":
        cp, other, mode = als(view_t, rank, cp_iterations, seed=seed, nonneg=nonneg), ViewKernel(view_c), "k"
    else:
        raise ValueError(f"init is auto, bound, temporal, contemporaneous, random or given, not {init!r}")
    n = {"i": 0, "k": 2}[mode]
    factors = cp.factors | {mode: np.zeros((view_t.shape[n], rank))}
    return factors | {mode: third_factor(other, factors, mode)}, branch, cp.passes + other.passes


def _init_many_modes(view_t: View, view_c: View, rank: int, cp_iterations: int, seed: int, nonneg: bool) -> tuple[dict[str, np.ndarray], str, int]:
    """As the temporal branch, for any number of modes: the mode that the first view groups, and the second doesn't, is solved for from the second."""
    grouped = [m for m in view_t.modes if view_t.groupings.get(m) is not None]
    if len(grouped) != 1 or view_c.groupings.get(grouped[0]) is not None:
        raise ValueError("a start for more than three modes needs a first view with one grouped mode, which the second one leaves whole")
    mode = grouped[0]
    cp, other = als(view_t, rank, cp_iterations, seed=seed, nonneg=nonneg), ViewKernel(view_c)
    factors = cp.factors | {mode: np.zeros((view_t.shape[view_t.modes.index(mode)], rank))}
    return factors | {mode: third_factor(other, factors, mode)}, "temporal", cp.passes + other.passes


def fit_coupled(views: list[View], rank: int, max_iter: int = ITERATIONS, tol: float | None = None, init: str = "auto", cp_iterations: int = CP_ITERATIONS, seed: int = 0, nonneg: bool = False, start: dict[str, np.ndarray] | None = None, placed: bool = False) -> Fit:
    """Factors of the fine cube from two views (temporal first, then contemporaneous) or more.

    Views are written once to the shared folder unless ``placed``. init="given" takes ``start``. view weights are the views' own.
    """
    began = time.perf_counter()
    if len({v.shape for v in views}) != 1:
        raise ValueError("the views are of cubes of different sizes")
    views = views if placed else [v.placed() for v in views]
    if start is not None or init == "given":
        factors, branch, passes = dict(start), "given", 0
    else:
        factors, branch, passes = init_coupled(views[0], views[1], rank, init, cp_iterations, seed, nonneg)
    if nonneg:
        factors = {m: np.maximum(f, 0) for m, f in factors.items()}
    kernels = [ViewKernel(v) for v in views]
    factors, trace = descend(kernels, factors, tuple(views[0].modes), max_iter, tol, nonneg=nonneg)
    return Fit(factors, trace, passes + sum(k.passes for k in kernels), branch, time.perf_counter() - began)


def fit_two_stage(view_t: View, view_c: View, rank: int, cp_iterations: int = 100, seed: int = 0) -> Fit:
    """The direct recovery: decompose a complete temporal view, then solve for the time factor on each tick's observed cells."""
    from finegrain.operators.identifiability import slab_systems

    began = time.perf_counter()
    view_t, view_c = view_t.placed(), view_c.placed()
    cp = als(view_t, rank, cp_iterations, seed=seed)
    coarse = view_c.coarse({"i": cp.factors["i"], "j": cp.factors["j"], "k": np.zeros((view_t.shape[2], rank))})
    c = np.zeros((view_t.shape[2], rank))
    for k, gram_, rhs, _ in slab_systems(view_c.cells, coarse):
        c[k] = solve_rows(gram_, rhs[None, :])[0] if np.linalg.matrix_rank(gram_) == rank else np.linalg.pinv(gram_) @ rhs
    return Fit(cp.factors | {"k": c}, [{"iter": n, "block": "cp", "loss": x, "reg": 0.0, "step": 0.0, "grad_sq": 0.0, "cells": 0} for n, x in enumerate(cp.losses)], cp.passes + 1, "temporal", time.perf_counter() - began)
