"""Fits in one task: the results of distributed passes, in few jobs."""

import numpy as np
import pytest
from helpers import cells

from finegrain.operators import groupings as G
from finegrain.operators import kernels
from finegrain.operators.baselines import coupled_matrix
from finegrain.plans import workloads as W

METHODS = ("coupled_matrix", "coupled_cp", "blind_cp", "cp_oracle")


def small(spark, absent, shape=(6, 4, 12)):
    rng = np.random.default_rng(5)
    x = np.einsum("ir,jr,kr->ijk", *(rng.random((n, 2)) for n in shape)) + 0.05 * rng.random(shape)
    x[rng.random(shape) < 0.1] = np.nan
    return W.Workload("small", cells(spark, x), shape, [W.Level("A-mod", G.period(shape[2], 3), G.fixed_size(shape[0], 2))], absent)


@pytest.mark.parametrize("absent", ["zero", "missing"])
def test_task_fits_as_passes_do(spark, monkeypatch, absent):
    monkeypatch.setattr(coupled_matrix, "GRID", (1, 3))
    monkeypatch.setattr(W, "GRID", (1, 3))
    w = small(spark, absent)
    held = W.run_level(w, w.levels[0], (2,), METHODS, iterations=3)
    for module in (W, coupled_matrix):
        monkeypatch.setattr(module, "HELD_CELLS", 0)
    spread = W.run_level(w, w.levels[0], (2,), METHODS, iterations=3)
    assert [r[:4] for r in held] == [r[:4] for r in spread]
    assert np.allclose([r[4] for r in held], [r[4] for r in spread], rtol=1e-6)


def test_a_small_fit_is_one_job(spark, monkeypatch):
    """Before, each pass was a job: F1 to F5."""
    w, asked = small(spark, "zero"), []
    own = kernels.cell_passes
    monkeypatch.setattr(kernels, "cell_passes", lambda passes: asked.append(1) or own(passes))
    assert len(W.run_level(w, w.levels[0], (2,), METHODS[1:], iterations=3)) == 3 and not asked
