"""Canonical polyadic decomposition by alternating least squares: starts of the coupled methods, and the oracle."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from finegrain.operators.held import HeldCells
from finegrain.operators.kernels import ViewKernel, others_gram, solve_rows
from finegrain.operators.views import View, make_view


@dataclass
class CpFit:
    factors: dict[str, np.ndarray]
    losses: list[float]
    passes: int

    @property
    def rank(self) -> int:
        return self.factors["i"].shape[1]


def random_factors(shape: tuple[int, ...], rank: int, seed: int, names: str = "ijk") -> dict[str, np.ndarray]:
    rng = np.random.default_rng(seed)
    return {m: rng.random((n, rank)) + 0.1 for m, n in zip(names, shape)}


def balanced(factors: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    """The same model with equal column norms in all modes."""
    norms = {m: np.maximum(np.linalg.norm(f, axis=0), 1e-300) for m, f in factors.items()}
    whole = np.prod(list(norms.values()), axis=0) ** (1 / len(factors))
    return {m: f / norms[m] * whole for m, f in factors.items()}


def als(view: View, rank: int, iterations: int = 10, masked: bool = False, seed: int = 0, start: dict[str, np.ndarray] | None = None, nonneg: bool = False) -> CpFit:
    """Factors of a coarse cube (its own indexes).

    masked=False: cells without a row are zeros, as starts want it. masked=True: they are missing; each update fills
    them with the model (expectation maximisation), which costs the same one pass.
    """
    shape = view.coarse_shape
    plain = View(view.cells, shape, {}, "missing" if masked else "zero", modes=view.modes)
    kernel = ViewKernel(plain)
    factors = start or random_factors(shape, rank, seed, view.modes)
    if start is None:  # the scale of the data, so that the first solves are not off by orders
        held = isinstance(plain.cells, HeldCells)
        total, n = (plain.cells.size, plain.cells.count) if held else plain.cells.selectExpr("coalesce(sum(abs(v)), 0D)", "count(v)").first()
        scale = max(total / max(n if masked else np.prod(shape), 1), 1e-12)
        level = np.einsum("r->", np.prod([f.mean(0) for f in factors.values()], axis=0))
        factors = {m: f * (scale / level) ** (1 / len(shape)) for m, f in factors.items()}
    losses = []
    for _ in range(iterations):
        for m in view.modes:
            s = kernel.block(factors, m)
            g = others_gram(factors, m)
            # Half the gradient is model minus data, times the others; so this is what least squares solves for.
            factors = factors | {m: solve_rows(g, factors[m] @ g - s.half)}
            if nonneg:
                factors[m] = np.maximum(factors[m], 0)
        losses.append(s.loss)
        factors = balanced(factors)
    return CpFit(factors, losses, kernel.passes)


def fit_cp(cells, shape: tuple[int, int, int], rank: int, iterations: int = 20, masked: bool = False, seed: int = 0, nonneg: bool = False) -> CpFit:
    """The oracle: a decomposition of the true cube, on its observed cells if masked."""
    absent = "missing" if masked else "zero"
    if not isinstance(cells, HeldCells):
        make_view(cells, shape, absent=absent)
    return als(View(cells, shape, {}, absent).placed(), rank, iterations, masked, seed, nonneg=nonneg)
