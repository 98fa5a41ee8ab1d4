"""What the experiment workloads run."""

import numpy as np
from helpers import cells

from finegrain.operators import groupings as G
from finegrain.operators.baselines.coupled_matrix import GRID
from finegrain.plans import workloads as W


def small(spark, shape=(6, 4, 12)):
    x = np.random.default_rng(3).random(shape)
    return W.Workload("small", cells(spark, x), shape, [W.Level("A-mod", G.period(shape[2], 3), G.fixed_size(shape[0], 2))])


def test_coupled_matrix_tries_the_whole_grid(spark, monkeypatch):
    tried = []

    def best(view_t, view_c, score, ranks=GRID, max_iter=10):
        tried.extend(ranks)
        return None, {r: abs(r - 25) / 100 for r in ranks}

    monkeypatch.setattr(W, "best_rank", best)
    w = small(spark)
    (row,) = W.run_level(w, w.levels[0], methods=("coupled_matrix",))
    assert tuple(tried) == GRID and row[2:5] == ("coupled_matrix", 25, 0.0)


def test_registered_workloads_are_whole(spark, monkeypatch):
    from finegrain import catalog

    calls = []

    def run(spark, sf_dir, names, methods, ranks=None, iterations=10, offset=0):
        calls.append((names, methods, ranks, iterations, offset))
        return spark.createDataFrame([], W.SCORE)

    monkeypatch.setattr(W, "run", run)
    for query in ("retail", "categories", "scale", "departments", "sensor", "embeddings", "mixed", "incident"):
        catalog.QUERIES[f"workload_{query}"](spark, "nowhere")
    assert {n for c in calls for n in c[0]} == {"retail_nbw", "retail_sbm", "dept_stm", "sensor_utd", "embed_lsd", "mixed_ntm", "incident_utd", *(f"category_top50/{t}" for t in W.TYPES)}
    assert all(c[2:4] == (None, 10) for c in calls) and {c[1] for c in calls} == {W.METHODS, ("blind_cp",)}
    monkeypatch.setattr(W, "missing_grid", lambda spark, sf_dir, *a, **kw: (a, kw))
    assert catalog.QUERIES["workload_missing"](spark, "nowhere") == ((), {})


def test_departments_of_few_suppliers(spark):
    from helpers import SF

    w = W.workload(spark, SF, "dept_stm")
    assert w.shape[0] == w.levels[0].u.n_members
    assert all(v.cells.count() for v in w.views(w.levels[0]))
