"""Cubes of more than three modes, limits that are checked, and one job for all views of a block."""

import numpy as np
import pytest
from helpers import cells, dense
from dense import model

from finegrain import shared
from finegrain.operators import groupings as G
from finegrain.operators.baselines import block_solvers, coupled_matrix
from finegrain.operators.baselines.block_solvers import ls_blocks
from finegrain.operators.baselines.closed_form import mean_split, min_norm_closed
from finegrain.operators.coupled import descend, fit_coupled
from finegrain.operators.cube import fold, numbered, ticks, unfold
from finegrain.operators.kernels import Pass, ViewKernel, cell_pass, cell_passes
from finegrain.operators.reconstruct import reconstruct, top_cells
from finegrain.operators.views import View, make_view
from finegrain.plans.planner import measured, with_holes_listed
from finegrain.plans.workloads import grid


def many(spark, x, names):
    at = np.argwhere(np.ones(x.shape))
    return spark.createDataFrame([(*map(int, p), float(x[tuple(p)])) for p in at], ", ".join(f"{m} long" for m in names) + ", v double")


def test_four_modes_from_a_careful_start(spark):
    rng = np.random.default_rng(4)
    shape, modes = (5, 4, 3, 12), "ijkl"
    f = [rng.random((n, 2)) + 0.1 for n in shape]
    x = np.einsum("ar,br,cr,dr->abcd", *f)
    df = many(spark, x, modes)
    t, c = make_view(df, shape, absent="zero", modes=modes, l=G.period(12, 3)), make_view(df, shape, absent="zero", modes=modes, i=G.chunk(5, 2))
    fit = fit_coupled([t, c], 2, 10, cp_iterations=30)
    assert fit.start == "temporal" and fit.monotone
    est = reconstruct(df.drop("v"), fit.factors, modes=modes).collect()
    error = sum((r.v - x[r.i, r.j, r.k, r.l]) ** 2 for r in est) / (x**2).sum()
    assert error < 0.01
    assert np.allclose([r.v for r in top_cells(spark, dict(zip(modes, f)), 9, modes).collect()], np.sort(x.ravel())[::-1][:9])
    signed = dict(zip(modes, [rng.normal(size=(n, 3)) for n in shape]))
    y = np.einsum("ar,br,cr,dr->abcd", *signed.values())
    assert np.allclose([r.v for r in top_cells(spark, signed, 9, modes).collect()], np.sort(y.ravel())[::-1][:9])
    with pytest.raises(ValueError):
        fit_coupled([make_view(df, shape, modes=modes, k=G.period(3, 3), l=G.period(12, 3)), c], 2, 1)


def test_passes_in_one_job_equal_passes_alone(spark):
    rng = np.random.default_rng(5)
    shape = (5, 4, 6)
    x = rng.random(shape)
    x[rng.random(shape) < 0.3] = np.nan
    df = cells(spark, x)
    f = {m: rng.random((n, 3)) for m, n in zip("ijk", shape)}
    small = {m: v[:2] for m, v in f.items()}
    passes = [Pass(df, f, "i"), Pass(df, f, "k", "raw"), Pass(df.where("i < 2 AND j < 2 AND k < 2"), small, "j", "model"), Pass(df.where("false"), f, "j")]
    mixed = [Pass(p.cells.repartition(3, "i", "j"), p.coarse, p.mode, p.values) for p in passes]  # partitions that a union may put together
    for group in (passes, mixed):
        for p, s in zip(passes, cell_passes(group)):
            own = cell_pass(p.cells, p.coarse, p.mode, p.values)
            assert np.allclose(own.rows, s.rows) and np.isclose(own.squares, s.squares) and own.cells == s.cells
    assert cell_passes([]) == []


@pytest.mark.parametrize("plan", ["observed", "gram", "complement"])
def test_projected_steps_know_their_loss(spark, plan):
    rng = np.random.default_rng(6)
    shape = (6, 4, 8)
    x = model(*(rng.random((n, 2)) for n in shape)) - 0.3
    w, u = G.period(8, 2), G.chunk(6, 2)
    views = [make_view(cells(spark, x), shape, absent="zero" if plan == "gram" else "missing", **g).placed() for g in ({"k": w}, {"i": u})]
    if plan == "complement":
        views = [with_holes_listed(View(v.cells.where("NOT (i = 1 AND j = 2 AND k = 0)"), shape, v.groupings)).placed() for v in views]
    kernels = [ViewKernel(v) for v in views]
    assert {k.plan for k in kernels} == {plan}
    f = {m: rng.random((n, 2)) for m, n in zip("ijk", shape)}
    new, trace = descend(kernels, f, ("i", "j", "k"), 2, nonneg=True, rebalance=False)
    assert all((v >= 0).all() for v in new.values())
    assert np.isclose(trace[-1]["loss"], sum(k.loss(new) for k in kernels), rtol=1e-8)
    assert all(b["loss"] <= a["loss"] * (1 + 1e-9) for a, b in zip(trace, trace[1:]))


def test_groupings_from_dictionaries(spark, monkeypatch):
    rows = [(n, ["b", None, "a", "b", "c"][n % 5], [3.0, None, 1.0, 2.0, 2.0][n % 5]) for n in range(11)]
    dim = spark.createDataFrame(rows, "idx long, name string, size double").repartition(3)
    named = G.by_column(dim, "name")
    assert named.n_groups == 3 and dict(zip(named.member.tolist(), named.grp.tolist())) == {n: "abc".index(x) for n, x, _ in rows if x}
    dim.createOrReplaceTempView("dim_of_sizes")
    want = [r.b for r in spark.sql("SELECT idx, ntile(4) OVER (ORDER BY size, idx) - 1 AS b FROM dim_of_sizes ORDER BY idx").collect()]
    assert G.by_ntile(dim, "size", 4).grp.tolist() == want
    assert G.by_ntile(dim, "size", 11).n_groups == 11
    table = spark.createDataFrame([(1, 0), (0, 0), (2, 1), (2, 0), (2, 0)], "m int, g int")
    both = G.from_table(table, "m", "g", 4, 2)
    assert list(zip(both.member.tolist(), both.grp.tolist())) == [(0, 0), (1, 0), (2, 0), (2, 1)]
    monkeypatch.setattr(G, "MEMBERS", 5)
    for f in (lambda: G.by_column(dim, "name"), lambda: G.by_ntile(dim, "size", 2), lambda: G.by_similarity(dim, ["size"], 2)):
        with pytest.raises(ValueError, match="join the grouping as a table"):
            f()


def test_parts_beyond_a_task_are_refused(spark, monkeypatch):
    shape = (6, 4, 8)
    x = cells(spark, np.ones(shape))
    t, c = make_view(x, shape, k=G.period(8, 2)), make_view(x, shape, i=G.chunk(6, 2))
    assert ls_blocks(t, c).count() == 192
    monkeypatch.setattr(block_solvers, "BLOCK_BYTES", 48 * 23)
    monkeypatch.setattr(coupled_matrix, "GROUP_BYTES", 100)
    with pytest.raises(ValueError, match="finer groups"):
        ls_blocks(t, c)
    with pytest.raises(ValueError, match="packed row"):
        coupled_matrix.packed_rows(t, c)


def test_closed_forms_read_each_view_once(spark):
    rng = np.random.default_rng(7)
    shape = (6, 4, 9)
    x = rng.random(shape)
    df = cells(spark, x)
    t, c = make_view(df, shape, absent="zero", k=G.period(9, 4)).placed(), make_view(df, shape, absent="zero", i=G.chunk(6, 2), j=G.fixed_size(4, 2)).placed()
    keys = grid(spark, shape)
    joins = lambda d: d._jdf.queryExecution().optimizedPlan().toString().count("Join ")
    assert joins(mean_split(keys, t, c)) == 5 and joins(min_norm_closed(keys, t, c)) == 10  # a group's table or a view at a time, and the periods of the blocks
    est = dense(min_norm_closed(keys, t, c), shape)
    assert np.allclose(est, dense(ls_blocks(t, c), shape), atol=1e-6)
    over = make_view(df, shape, k=G.calendar(9, G.overlapping_calendar(9, 4)))
    share = np.full(shape, np.nan)
    for k in range(9):
        own = [(a, b) for a, b in G.overlapping_calendar(9, 4) if a <= k < b]
        if own:
            share[:, :, k] = np.mean([x[:, :, a:b].sum(2) / (b - a) for a, b in own], axis=0)
    even = np.repeat(np.repeat(x.reshape(2, 3, 2, 2, 9).sum((1, 3)) / 6, 3, 0), 2, 1)
    want = np.where(np.isnan(share), even, (np.nan_to_num(share) + even) / 2)
    assert np.allclose(dense(mean_split(keys, over, c), shape), want) and np.allclose(dense(mean_split(keys, c, over), shape), want)


def test_unfold_fold_number_and_ticks(spark):
    x = np.random.default_rng(2).random((3, 2, 4))
    x[1, 1, 2] = np.nan
    df = cells(spark, x)
    assert np.array_equal(dense(fold(unfold(df, 4), 4), x.shape), x, equal_nan=True)
    rows = spark.range(1000, numPartitions=7).selectExpr("(id * 7919) % 1000 AS a")
    got = numbered(rows, ["a"]).collect()
    assert all(r.a == r.idx for r in got) and len(got) == 1000
    assert numbered(rows.limit(0), ["a"]).collect() == []
    days = ticks(spark, "1995-01-02", "1996-03-01").collect()
    assert len(days) == 425 and (days[-1].month, days[-1].quarter, days[-1].half_year, days[-1].week) == (14, 4, 2, 60)


def test_costs_as_spark_counts_them(spark):
    x = shared.table(cells(spark, np.ones((6, 4, 8))))
    view = make_view(x, (6, 4, 8), k=G.period(8, 2)).placed()
    f = {m: np.ones((n, 2)) for m, n in zip("ijk", view.coarse_shape)}
    sums, cost = measured(spark, lambda: cell_pass(view.cells, f, "i"))
    assert sums.cells == 96 and cost["rows_read"] == 96 and cost["bytes_read"] > 0 and 0 < cost["bytes_shuffled"] < 5000 and cost["stages"] >= 2


def test_cells_outside_the_cube_are_an_error(spark):
    x = cells(spark, np.ones((6, 4, 8)))
    assert make_view(x, (6, 4, 8), k=G.period(8, 2)).cells.count() == 96
    for shape, groups in (((5, 4, 8), {"k": G.period(8, 2)}), ((6, 4, 7), {"k": G.period(7, 2)}), ((6, 3, 8), {"i": G.chunk(6, 2)})):
        with pytest.raises(Exception, match="outside the cube"):
            make_view(x, shape, **groups).cells.count()


def test_together_keeps_the_order_and_raises():
    assert shared.together([lambda n=n: n * n for n in range(9)]) == [n * n for n in range(9)]
    assert shared.together([]) == []
    with pytest.raises(ZeroDivisionError):
        shared.together([lambda: 1, lambda: 1 // 0])


def test_a_cluster_needs_a_shared_folder(monkeypatch):
    class Context:
        master = "spark://somewhere:7077"

        class _jsc:  # noqa: N801
            @staticmethod
            def sc():
                return type("", (), {"getCheckpointDir": staticmethod(lambda: type("", (), {"isEmpty": staticmethod(lambda: True)}))})

    session = type("", (), {"conf": type("", (), {"get": staticmethod(lambda name, default: default)}), "sparkContext": Context})
    with pytest.raises(RuntimeError, match="checkpoint.dir"):
        shared.shared_dir(session)
