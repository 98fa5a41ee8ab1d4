import numpy as np
import pytest
from helpers import cells, dense
from dense import model

from finegrain.operators import groupings as G
from finegrain.operators.coupled import fit_coupled
from finegrain.operators.partitioned import WideView, fit_coupled_wide
from finegrain.operators.views import View, make_view
from finegrain.plans.workloads import grid


@pytest.mark.parametrize("absent", ["zero", "missing"])
def test_partitioned_equals_broadcast(spark, absent):
    shape = (9, 4, 6)
    rng = np.random.default_rng(3)
    x = model(*(rng.random((n, 2)) for n in shape))
    if absent == "missing":
        x[rng.random(shape) < 0.2] = np.nan
    u, w = G.chunk(9, 3), G.period(6, 2)
    t, c = make_view(cells(spark, x), shape, absent=absent, k=w), make_view(cells(spark, x), shape, absent=absent, i=u)
    start = {m: rng.random((n, 2)) for m, n in zip("ijk", shape)}
    areas = u.frame(spark)
    wide = fit_coupled_wide(t, c.cells, areas, 3, 2, 1, 4, start)
    plain = fit_coupled([t, c], 2, 1, start=start)
    assert np.allclose(wide.losses, plain.losses)
    keys = grid(spark, shape)
    assert np.allclose(dense(wide.reconstruct(keys), shape), model(*(plain.factors[m] for m in "ijk")))


def test_blocks_meet_without_a_shuffle(spark):
    shape = (9, 4, 6)
    t = make_view(cells(spark, np.ones(shape)), shape, absent="zero", k=G.period(6, 2))
    fit = fit_coupled_wide(t, make_view(cells(spark, np.ones(shape)), shape, i=G.chunk(9, 3)).cells, G.chunk(9, 3).frame(spark), 3, 2, 1, 4)
    assert fit.losses[-1] <= fit.losses[0]
    view = WideView(t, 4)
    plan = view.first_mode(fit.rows, {"j": fit.factors["j"], "k": G.period(6, 2).apply(fit.factors["k"])}, np.zeros((3, 2)), False)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan.split("Initial Plan")[0]


@pytest.mark.parametrize("absent", ["zero", "missing"])
def test_double_grouping_and_a_view_with_holes(spark, absent):
    """The second mode grouped too, and a contemporaneous view whose absent cells are missing beside a temporal one without holes."""
    shape = (9, 4, 6)
    rng = np.random.default_rng(4)
    x = model(*(rng.random((n, 2)) for n in shape))
    u, v, w = G.chunk(9, 3), G.fixed_size(4, 2), G.period(6, 2)
    t = make_view(cells(spark, x), shape, absent=absent, k=w)
    c = make_view(cells(spark, x), shape, i=u, j=v)
    c = View(c.cells.where("NOT (i = 1 AND j = 0 AND k = 2)"), shape, c.groupings)
    start = {m: rng.random((n, 2)) for m, n in zip("ijk", shape)}
    wide = fit_coupled_wide(t, c.cells, u.frame(spark), 3, 2, 2, 4, start, second=v, absent_c="missing")
    plain = fit_coupled([t, c], 2, 2, start=start)
    assert np.allclose(wide.losses[:3], plain.losses[:3]) and wide.losses[-1] <= wide.losses[0]
    one = fit_coupled([t, c], 2, 1, start=start)
    assert np.allclose(dense(fit_coupled_wide(t, c.cells, u.frame(spark), 3, 2, 1, 4, start, second=v, absent_c="missing").reconstruct(grid(spark, shape)), shape), model(*(one.factors[m] for m in "ijk")))
