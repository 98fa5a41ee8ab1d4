"""Kernels, steps, fits and estimators against dense references and known answers."""

import numpy as np
import pytest
from helpers import cells, dense
from dense import loss, matrix, model, numeric_gradient, observe

from finegrain.operators import groupings as G
from finegrain.operators import metrics
from finegrain.operators.baselines.block_solvers import dct_basis, ls_blocks
from finegrain.operators.baselines.closed_form import mean_split, min_norm_closed
from finegrain.operators.baselines.coupled_matrix import fit_coupled_matrix
from finegrain.operators.blind import blind_kernels, chunk_sums, column_sum_penalty, fit_blind
from finegrain.operators.coupled import SumPenalty, choose_branch, coupled_loss, exact_step, fit_coupled, fit_two_stage, half_gradient
from finegrain.operators.cpd import als, fit_cp
from finegrain.operators.identifiability import match_factors, rank_bound, ranks_for, slab_check, slab_rank
from finegrain.operators.kernels import ViewKernel, cell_pass, expression_pass
from finegrain.operators.reconstruct import reconstruct, reconstruct_sql, top_cells
from finegrain.operators.views import View, coarser, make_view, masked, mode_products
from finegrain.plans import planner
from finegrain.plans.workloads import grid
from finegrain.sources.tables import factor_frame, load_cells, load_fit, save_cells, save_fit

SHAPE = (6, 5, 12)
RNG = np.random.default_rng(4)
U, V, W = G.chunk(6, 3), G.fixed_size(5, 2), G.period(12, 4)


def factors(rank=3, seed=1, shape=SHAPE):
    rng = np.random.default_rng(seed)
    return {m: rng.random((n, rank)) for m, n in zip("ijk", shape)}


def holey(x, share=0.2, seed=9):
    return np.where(np.random.default_rng(seed).random(x.shape) < share, np.nan, x)


@pytest.fixture(scope="module")
def cube():
    return model(*factors(2, 7).values()) + 0.1 * np.random.default_rng(3).random(SHAPE)


@pytest.mark.parametrize("groups", [{"k": W}, {"i": U}, {"i": U, "j": V}, {"i": U, "j": V, "k": W}, {"k": G.calendar(12, [(0, 4), (2, 6), (8, 12)])}, {"i": G.chunk(6, 3, "avg")}])
def test_mode_products(spark, cube, groups):
    got = dense(mode_products(cells(spark, cube), groups), tuple(groups[m].n_groups if m in groups else n for m, n in zip("ijk", SHAPE)))
    want = observe(cube, *(groups.get(m) for m in "ijk"))
    assert np.allclose(np.nan_to_num(got), want)


def test_missing_rules_and_ladder(spark, cube):
    x = holey(cube)
    some = dense(mode_products(cells(spark, x), {"k": W}), (6, 5, 3))
    every = dense(mode_products(cells(spark, x), {"k": W}, "all"), (6, 5, 3))
    full = ~np.isnan(x.reshape(6, 5, 3, 4)).any(3)
    assert (np.isnan(every) == ~full).all() and np.allclose(np.nan_to_num(some), np.nansum(x.reshape(6, 5, 3, 4), 3))
    t = make_view(cells(spark, cube), SHAPE, k=G.period(12, 2))
    up = coarser(t, k=G.fixed_size(6, 3))
    assert np.allclose(dense(up.cells, (6, 5, 2)), observe(cube, w=G.period(12, 6)))
    assert np.allclose(matrix(up.groupings["k"]), matrix(G.period(12, 6)))


def views_of(spark, cube, plan):
    x = holey(cube) if plan != "gram" else cube
    t, c = observe(cube, w=W), observe(cube, U, V)
    if plan != "gram":
        t, c = holey(t, 0.2, 1), holey(c, 0.2, 2)
    out = []
    for y, groups in ((t, {"k": W}), (c, {"i": U, "j": V})):
        v = View(cells(spark, y), SHAPE, groups, "zero" if plan == "gram" else "missing")
        out.append((planner.with_holes_listed(v, 10.0) if plan == "complement" else v, y, groups))
    return out


@pytest.mark.parametrize("plan", ["observed", "gram", "complement"])
def test_gradients_steps_and_loss(spark, cube, plan):
    views = views_of(spark, cube, plan)
    kernels, f = [ViewKernel(v) for v, _, _ in views], factors()
    assert {k.plan for k in kernels} == {plan}
    ref = [(y, g) for _, y, g in views]
    assert np.isclose(coupled_loss(f, [v for v, _, _ in views]), loss(f, ref))
    for m in "ijk":
        half, before, _ = half_gradient(kernels, f, m)
        assert np.allclose(2 * half, numeric_gradient(lambda x, m=m: loss(f | {m: x}, ref), f[m]), rtol=1e-6, atol=1e-6)
        step, top, below = exact_step(kernels, f, m, 2 * half)
        at = lambda a, m=m, half=half: loss(f | {m: f[m] - a * 2 * half}, ref)
        assert at(step) <= min(at(step * 1.01), at(step * 0.99)) and np.isclose(at(step), before - top**2 / below, rtol=1e-6)


def test_expression_kernel_equals_arrow_kernel(spark, cube):
    f, x = factors(2), cells(spark, holey(cube))
    want = cell_pass(x, f, "j").rows
    got = expression_pass(x, {m: factor_frame(spark, a) for m, a in f.items()}, "j", 2).collect()
    assert np.allclose([[r.g0, r.g1] for r in sorted(got)], want)
    one = {m: a[:, :1] for m, a in f.items()}
    assert cell_pass(x, one, "k").cells == int((~np.isnan(holey(cube))).sum())


def test_blind_gradients_and_penalty(spark, cube):
    t, c = observe(cube, w=W), observe(cube, U)
    views = [View(cells(spark, holey(t)), (6, 5, 3), {}), View(cells(spark, holey(c)), (3, 5, 12), {})]
    kernels, penalty = blind_kernels(*views), SumPenalty(3.0, np.ones(12))
    f = factors() | {"it": RNG.random((3, 3)), "kt": RNG.random((3, 3))}

    def total(g):
        return np.nansum((model(g["i"], g["j"], g["kt"]) - holey(t)) ** 2) + np.nansum((model(g["it"], g["j"], g["k"]) - holey(c)) ** 2) + column_sum_penalty(g["k"], g["kt"], 3.0)

    for name in ("i", "it", "j", "k", "kt"):
        half, _, _ = half_gradient(kernels, f, name, penalty)
        assert np.allclose(2 * half, numeric_gradient(lambda x, n=name: total(f | {n: x}), f[name]), rtol=1e-6, atol=1e-6)
        step, _, _ = exact_step(kernels, f, name, 2 * half, penalty)
        at = lambda a, n=name, half=half: total(f | {n: f[n] - a * 2 * half})
        assert at(step) <= min(at(step * 1.02), at(step * 0.98))
    # The scale between the views is free without the penalty, and fixed by it.
    scaled = f | {"i": 2 * f["i"], "kt": f["kt"] / 2}
    assert np.isclose(total(scaled) - column_sum_penalty(scaled["k"], scaled["kt"], 3.0), total(f) - column_sum_penalty(f["k"], f["kt"], 3.0))
    assert not np.isclose(total(scaled), total(f))


def test_als_and_masked_als(spark):
    x = model(*factors(2, 5).values())
    assert metrics.nde_model(cells(spark, x), fit_cp(cells(spark, x), SHAPE, 2, 12).factors) < 1e-2
    fit = als(View(cells(spark, holey(x)), SHAPE, {}).placed(), 2, 12, masked=True)
    assert np.nansum((model(*(fit.factors[m] for m in "ijk")) - x) ** 2) / (x**2).sum() < 2e-2
    assert all(b <= a * (1 + 1e-9) for a, b in zip(fit.losses, fit.losses[1:]))


@pytest.mark.parametrize("init", ["auto", "bound", "temporal", "contemporaneous", "random", "given"])
def test_coupled_descends_from_every_start(spark, init):
    x = model(*factors(2, 5).values())
    t, c = make_view(cells(spark, x), SHAPE, k=W), make_view(cells(spark, x), SHAPE, i=U)
    fit = fit_coupled([t, c], 2, 2, cp_iterations=2, init=init, start=factors(2, 6) if init == "given" else None)
    assert all(b <= a * (1 + 1e-9) + 1e-12 for a, b in zip(fit.losses, fit.losses[1:]))
    assert np.isclose(fit.losses[-1], coupled_loss(fit.factors, [t, c]), rtol=1e-5, atol=1e-9)


def test_coupled_variants(spark, cube):
    x = cells(spark, cube)
    t, c = make_view(x, SHAPE, absent="zero", k=W), make_view(x, SHAPE, absent="zero", i=U)
    same = make_view(x, SHAPE, absent="zero", i=U, j=G.fixed_size(5, 1))  # an identity grouping, given explicitly
    one, two = (fit_coupled([t, v], 2, 1, cp_iterations=2, init="temporal") for v in (c, same))
    assert all(np.allclose(one.factors[m], two.factors[m]) for m in "ijk")
    third = make_view(x, SHAPE, absent="zero", j=V, k=W)
    three = fit_coupled([t, c, third], 2, 1, cp_iterations=1)
    assert three.losses[-1] <= three.losses[0]
    nonneg = fit_coupled([t, c], 2, 2, cp_iterations=2, nonneg=True)
    assert min(f.min() for f in nonneg.factors.values()) >= 0 and nonneg.losses[-1] <= nonneg.losses[0]
    early = fit_coupled([t, c], 2, 50, tol=0.5, cp_iterations=1)
    assert len(early.trace) < 150
    assert one.trace_frame(spark).count() == len(one.trace)


def test_branches():
    spark = None
    t, c = View(spark, (25, 25, 357), {"k": G.period(357, 51)}), View(spark, (25, 25, 357), {"i": G.chunk(25, 5)})
    assert choose_branch(t, c, "auto") == "contemporaneous" and choose_branch(t, c, "temporal") == "temporal"
    assert choose_branch(View(spark, (25, 25, 357), {"k": G.period(357, 4)}), c, "bound") == "temporal"


def test_two_stage_recovers_exactly(spark):
    shape = (6, 5, 8)
    rng = np.random.default_rng(12)
    true = {m: rng.standard_normal((n, 2)) for m, n in zip("ijk", shape)}
    x = model(*true.values())
    t, c = make_view(cells(spark, x), shape, k=G.period(8, 2)), make_view(cells(spark, x), shape, i=G.chunk(6, 3))
    fit = fit_two_stage(t, c, 2, 25)
    assert metrics.nde_model(cells(spark, x), fit.factors) < 1e-4
    assert match_factors(true, fit.factors)[0] > 0.99


def test_blind_runs_and_partial_knowledge(spark):
    x = model(*factors(2, 5).values())
    t, c = make_view(cells(spark, x), SHAPE, k=W), make_view(cells(spark, x), SHAPE, i=U)
    base = [fit_blind(t, c, 2, mu=mu, max_iter=2, cp_iterations=1, known=known) for mu, known in ((100.0, None), ("relative", None), (1.0, {"W": W}), (1.0, {"U": U}))]
    for fit in base:
        assert fit.factors["k"].shape == (12, 2) and fit.losses[-1] <= fit.losses[0] * 1.5
    assert "kt" in base[0].factors and np.allclose(chunk_sums(np.ones((10, 1)), 4).ravel(), [3, 2, 3, 2])
    with pytest.raises(ValueError):
        fit_blind(t, make_view(cells(spark, x), SHAPE, i=U, j=V), 2)


@pytest.mark.parametrize("second", [None, V])
def test_least_squares_against_pseudo_inverse(spark, cube, second):
    x = cells(spark, cube)
    t, c = make_view(x, SHAPE, k=W), make_view(x, SHAPE, i=U, j=second)
    rows = np.array([np.concatenate([observe(e.reshape(SHAPE), w=W).ravel(), observe(e.reshape(SHAPE), U, second).ravel()]) for e in np.eye(cube.size)]).T
    y = np.concatenate([observe(cube, w=W).ravel(), observe(cube, U, second).ravel()])
    want = (np.linalg.pinv(rows, 1e-10) @ y).reshape(SHAPE)
    keys = grid(spark, SHAPE)
    assert np.allclose(dense(min_norm_closed(keys, t, c), SHAPE), want, atol=1e-8)
    assert np.allclose(dense(ls_blocks(t, c), SHAPE), want, atol=1e-6)
    hidden = masked(t, t.cells.where("(i + j + k) % 4 != 0"))
    seen = ~np.isnan(dense(hidden.cells, (6, 5, 3))).ravel()
    keep = np.concatenate([seen, np.ones(len(y) - len(seen), bool)])
    assert np.allclose(dense(ls_blocks(hidden, c), SHAPE), (np.linalg.pinv(rows[keep], 1e-10) @ y[keep]).reshape(SHAPE), atol=1e-5)
    d = np.array([np.diff(e.reshape(SHAPE), axis=2).ravel() for e in np.eye(cube.size)]).T
    smooth = np.linalg.solve(rows.T @ rows + 0.5 * d.T @ d, rows.T @ y).reshape(SHAPE)
    assert np.allclose(dense(ls_blocks(t, c, "smooth", 0.5), SHAPE), smooth, atol=1e-5)
    sparse = dense(ls_blocks(t, c, "sparse", 0.1, 0.01), SHAPE)
    assert sparse.min() >= 0 and np.linalg.norm(sparse - cube) < np.linalg.norm(cube)


def test_dct_basis_is_orthonormal():
    assert np.allclose(dct_basis(9) @ dct_basis(9).T, np.eye(9))


def test_coupled_matrix(spark):
    x = model(*factors(2, 5).values())
    t, c = make_view(cells(spark, x), SHAPE, k=W), make_view(cells(spark, x), SHAPE, i=U, j=V)
    fit = fit_coupled_matrix(t, c, 2, 2)
    assert metrics.nde_value(cells(spark, x), fit.cells()) < 1e-8
    noisy = fit_coupled_matrix(make_view(cells(spark, holey(x)), SHAPE, k=W), c, 2, 2)
    assert noisy.losses[-1] <= noisy.losses[0] * (1 + 1e-9)
    assert fit_coupled_matrix(t, c, 2, 1, nonneg=True).q.min() >= 0


def test_hand_fixtures(spark):
    x = np.array([[[1.0, 3.0]], [[5.0, 7.0]]])
    t, c = make_view(cells(spark, x), x.shape, k=G.period(2, 2)), make_view(cells(spark, x), x.shape, i=G.fixed_size(2, 2))
    keys = grid(spark, x.shape)
    mean = mean_split(keys, t, c)
    assert dense(mean, x.shape).ravel().tolist() == [2.5, 3.5, 4.5, 5.5]
    assert np.allclose(dense(min_norm_closed(keys, t, c), x.shape), x)
    assert np.isclose(metrics.nde_value(cells(spark, x), mean), 5 / 84)
    ones = np.ones((2, 1, 4))
    t, c = make_view(cells(spark, ones), ones.shape, k=G.period(4, 2)), make_view(cells(spark, ones), ones.shape, i=G.fixed_size(2, 2))
    for estimate in (mean_split(grid(spark, ones.shape), t, c), min_norm_closed(grid(spark, ones.shape), t, c), ls_blocks(t, c)):
        assert np.allclose(dense(estimate, ones.shape), 1)
    assert [rank_bound(93, 50, 18, 50, 98), rank_bound(93, 50, 9, 50, 33), rank_bound(49, 17, 7, 17, 12)] == [290, 103, 12]
    assert ranks_for((93, 50, 397), (18, 50, 397), 98) == [10, 25, 40] and ranks_for((49, 17, 365), (7, 17, 365), 12) == [10]
    flat = {m: np.ones((n, 1)) for m, n in zip("ijk", (4, 3, 4))}
    full = np.ones((4, 3, 4))
    kernels = [ViewKernel(make_view(cells(spark, full), full.shape, k=G.period(4, 2))), ViewKernel(make_view(cells(spark, full), full.shape, i=G.fixed_size(4, 2)))]
    half, at, _ = half_gradient(kernels, flat, "i")
    assert np.allclose(half, 0) and at == 0 and exact_step(kernels, flat, "i", 2 * half)[0] == 0


def test_identifiability(spark, cube):
    c = make_view(cells(spark, holey(cube, 0.5)), SHAPE, i=U)
    from finegrain.operators.masks import starve_slab

    starved = starve_slab(c.cells, 3, 1)
    poor = {r.k for r in slab_check(starved, 13, 2).collect() if not r.enough}
    assert {3, 12} <= poor
    f = factors()
    ranks = slab_rank(starved, {"i": U.apply(f["i"]), "j": f["j"]})
    assert ranks[3] == 1 and max(ranks.values()) == 3


def test_reconstruction_and_metrics(spark, cube, tmp_path):
    f = factors()
    want = model(*f.values())
    keys = grid(spark, SHAPE)
    for got in (reconstruct(keys, f), reconstruct_sql(keys, f)):
        assert np.allclose(dense(got, SHAPE), want)
    top = [r.v for r in top_cells(spark, f, 7).collect()]
    assert np.allclose(top, np.sort(want.ravel())[::-1][:7])
    x = cells(spark, cube)
    e = ((cube - want) ** 2).sum() / (cube**2).sum()
    assert np.isclose(metrics.nde_gram(x, f), e) and np.isclose(metrics.nde_model(x, f), e) and np.isclose(metrics.nde_value(x, reconstruct(keys, f), "all"), e)
    save_fit(spark, f, str(tmp_path / "fit"), {"rank": 3})
    back, meta = load_fit(spark, str(tmp_path / "fit"))
    assert meta == {"rank": 3} and all(np.array_equal(back[m], f[m]) for m in "ijk")
    save_cells(x, str(tmp_path / "cells"), 4)
    assert load_cells(spark, str(tmp_path / "cells"), (4, 7), 4).count() == 6 * 5 * 4


def test_refusals(spark, cube):
    from finegrain.operators.cube import observed

    with pytest.raises(ValueError):
        make_view(cells(spark, cube), SHAPE, i=G.chunk(7, 2))
    with pytest.raises(ValueError):
        mode_products(cells(spark, cube), {"k": W}, "some")
    with pytest.raises(Exception, match="NaN"):
        observed(spark.createDataFrame([(0, 0, 0, float("nan"))], "i long, j long, k long, v double")).collect()
    empty = View(cells(spark, np.full(SHAPE, np.nan)), SHAPE, {"k": W})
    assert ViewKernel(empty).loss(factors()) == 0


def test_four_modes(spark):
    """The kernels take any number of modes: two views of a 4-mode cube, gradient against differences, descent."""
    rng = np.random.default_rng(8)
    shape, modes = (3, 4, 2, 6), "ijkl"
    x = np.einsum("ar,br,cr,dr->abcd", *(rng.random((n, 2)) for n in shape))
    at = np.argwhere(np.ones(shape))
    df = spark.createDataFrame([(*map(int, p), float(x[tuple(p)])) for p in at], "i long, j long, k long, l long, v double")
    t = make_view(df, shape, modes=modes, l=G.period(6, 3))
    c = make_view(df, shape, modes=modes, i=G.chunk(3, 1), j=G.chunk(4, 2))
    assert t.coarse_shape == (3, 4, 2, 2) and c.coarse_shape == (1, 2, 2, 6)
    fit = fit_coupled([t, c], 2, 2, init="random")
    assert set(fit.factors) == set(modes) and all(b <= a * (1 + 1e-9) for a, b in zip(fit.losses, fit.losses[1:]))
    assert als(View(df, shape, {}, "zero", modes=modes), 2, 3).losses[-1] < (x**2).sum()
