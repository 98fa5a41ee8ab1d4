"""Parts without missing cells are solved at once, with the results of conjugate gradients."""

import numpy as np
import pytest

from finegrain.operators import groupings as G
from finegrain.operators.baselines import block_solvers


@pytest.mark.parametrize("apart", [True, False])
def test_whole_parts_are_solved_at_once(monkeypatch, apart):
    """Before, each part without missing cells took conjugate gradients, and a sparse one took them 60 times."""
    rng = np.random.default_rng(2)
    u = G.fixed_size(4, 4) if apart else G.Grouping(np.array([0, 1, 1, 2, 3]), np.array([0, 0, 1, 1, 1]), np.array([1.0, 0.5, 0.5, 1.0, 1.0]), 4, 2)
    w, share = G.period(11, 3), np.array([1.0, 2.0])
    b = block_solvers.Block(u, w, share, np.ones((4, 2, 4)), np.ones((4, 2, 4)), np.ones((u.n_groups, 11)), np.ones((u.n_groups, 11)))
    x = rng.random((4, 2, 11))
    b.yt, b.yc = b.temporal(x), b.contemporaneous(x) + 0.1 * rng.random((u.n_groups, 11))
    want = {lam: block_solvers.conjugate_gradients(lambda y, lam=lam: b.normal(y) + lam * block_solvers.smoothness(y), b.right(), 1e-13, 5000) for lam in (0.0, 0.01, 1.0)}
    monkeypatch.setattr(block_solvers, "conjugate_gradients", None)
    for lam, y in want.items():
        assert np.allclose(block_solvers.solve_smooth(b, lam), y, atol=1e-6)
    assert (block_solvers.solve_sparse(b, 0.1, 0.1) >= 0).all() and len(b.known) == 5
