"""All methods of a cube that a task holds: the results of the distributed ones, in few jobs."""

import numpy as np
import pytest
from helpers import cells

from finegrain.operators import groupings as G
from finegrain.operators.baselines import coupled_matrix
from finegrain.plans import workloads as W

LEVELS = {
    "groups": lambda n: W.Level("groups", G.period(n[2], 3), G.fixed_size(n[0], 2)),
    "double": lambda n: W.Level("double", G.period(n[2], 5, 2), G.fixed_size(n[0], 4), G.fixed_size(n[1], 3)),
    "averages": lambda n: W.Level("averages", G.period(n[2], 3, 0, "avg"), G.chunk(n[0], 2, "avg")),
    "gaps": lambda n: W.Level("gaps", G.calendar(n[2], G.gapped_calendar(n[2], 2, 3)), G.Grouping.of([0, 1, 0, -1, 1, 1])),
    "overlaps": lambda n: W.Level("overlaps", G.calendar(n[2], G.overlapping_calendar(n[2], 4)), G.fixed_size(n[0], 2)),
}


def cube(spark, level, absent, shape=(6, 4, 12)):
    rng = np.random.default_rng(7)
    x = np.einsum("ir,jr,kr->ijk", *(rng.random((n, 2)) for n in shape)) + 0.05 * rng.random(shape)
    x[rng.random(shape) < 0.3] = np.nan
    x[0], x[:, 1, :6] = np.nan, np.nan  # a first-mode index and periods without any cell
    return W.Workload("small", cells(spark, x), shape, [LEVELS[level](shape)], absent, signed=level == "averages")


@pytest.mark.parametrize(("level", "absent"), [("groups", "zero"), ("groups", "missing"), ("double", "zero"), ("averages", "missing"), ("gaps", "zero"), ("overlaps", "missing")])
def test_tasks_score_as_joins_do(spark, monkeypatch, level, absent):
    monkeypatch.setattr(W, "GRID", (1, 3))
    monkeypatch.setattr(W, "LAMBDAS", (0.1, 10.0))
    monkeypatch.setattr(W, "PARTS_A_TASK", (5, 2))
    w, methods = cube(spark, level, absent), W.METHODS + ("blind_cp",)
    held = W.run_level(w, w.levels[0], (2,), methods, iterations=3)
    for module in (W, coupled_matrix):
        monkeypatch.setattr(module, "HELD_CELLS", 0)
    spread = W.run_level(w, w.levels[0], (2,), methods, iterations=3)
    assert [r[:4] for r in held] == [r[:4] for r in spread] and [r[5] for r in held] == [r[5] for r in spread]
    assert len(held) == 8 - (level == "double") - (level == "averages")
    assert np.allclose([r[4] for r in held], [r[4] for r in spread], rtol=1e-5)


def test_a_level_is_few_jobs(spark, monkeypatch):
    """before, each method had jobs of its own, each with plans and stages that the driver keeps."""
    w, tracker = cube(spark, "groups", "zero"), spark.sparkContext.statusTracker()
    spark.sparkContext.setJobGroup("level", "one level")
    try:
        rows = W.run_level(w, w.levels[0], (1, 2), W.METHODS, iterations=2)
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(rows) == 9
    jobs = [tracker.getJobInfo(j) for j in tracker.getJobIdsForGroup("level")]
    assert 2 <= len(jobs) <= 8
    tasks = {info.numTasks for j in jobs for s in j.stageIds if (info := tracker.getStageInfo(s))}
    assert 2 + len(W.LAMBDAS) + 1 + 2 * 2 in tasks  # side by side, each fit of the methods other than coupled_matrix
