"""Choices made before Spark sees a fit, and their explanation."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace
from typing import TypeVar

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from finegrain.operators.views import View
from finegrain.plans.costs import fit_cost, placement


T = TypeVar("T")


def _stages(spark: SparkSession) -> dict[int, dict[str, int]]:
    """Counters of the stages that Spark still remembers."""
    sc = spark.sparkContext
    jvm = sc._gateway
    found = sc._jsc.sc().statusStore().stageList(None, False, False, jvm.new_array(jvm.jvm.double, 0), jvm.jvm.java.util.ArrayList()).iterator()
    out = {}
    while found.hasNext():
        s = found.next()
        out[s.stageId()] = {"tasks": s.numTasks(), "rows_read": s.inputRecords(), "bytes_read": s.inputBytes(), "bytes_shuffled": s.shuffleWriteBytes(), "bytes_spilled": s.diskBytesSpilled()}
    return out


def measured(spark: SparkSession, job: Callable[[], T]) -> tuple[T, dict[str, float]]:
    """A job's result, and what it cost by Spark's own counters: stages, tasks, rows and bytes read, bytes shuffled and spilled, seconds.

    Jobs of other threads count too. Spark remembers spark.ui.retainedStages stages: more than that in one job are not all counted.
    """
    before = max(_stages(spark), default=-1)
    began = time.perf_counter()
    result = job()
    seconds = time.perf_counter() - began
    time.sleep(0.2)  # counters come with the last events
    own = [c for n, c in _stages(spark).items() if n > before]
    return result, {"seconds": seconds, "stages": len(own)} | {k: sum(c[k] for c in own) for k in ("tasks", "rows_read", "bytes_read", "bytes_shuffled", "bytes_spilled")}


def residual_plan(view: View, observed: int | None = None) -> str:
    """The cheapest plan that is right for what absent cells mean.

    Absent cells that are zeros need no reading (gram). With missing cells, the holes are corrected for if they are listed and fewer
    than half of the stored cells (complement); otherwise the observed cells are read twice.
    """
    if view.absent == "zero":
        return "gram" if view.holes is None else "complement"
    return "observed"


def with_holes_listed(view: View, most_share: float = 0.5) -> View:
    """A view whose few missing cells become a list, if they are few: its fits then read the stored cells once a block.

    The complement is made from a range over the coarse cube, so it is only tried for cubes that the observed cells nearly fill.
    """
    total = int(np.prod(view.coarse_shape))
    stored = view.cells.where("v IS NOT NULL").count()
    if view.absent == "zero" or total - stored > most_share * stored:
        return view
    n_i, n_j, n_k = view.coarse_shape
    at = view.cells.sparkSession.range(total)
    every = at.select(F.floor(F.col("id") / (n_j * n_k)).alias("i"), F.pmod(F.floor(F.col("id") / n_k), F.lit(n_j)).alias("j"), F.pmod("id", F.lit(n_k)).alias("k"))
    return replace(view, absent="zero", holes=every.join(view.cells.where("v IS NOT NULL"), ["i", "j", "k"], "left_anti"))


def explain(views: list[View], rank: int, iterations: int = 10) -> str:
    """The plan of a coupled fit as text."""
    shape = views[0].shape
    lines = [f"cube {shape}, rank {rank}, factors {placement(shape, rank)}"]
    for n, v in enumerate(views):
        cells = v.cells.count()
        holes = v.holes.count() if v.holes is not None else 0
        plan = residual_plan(v)
        cost = fit_cost(plan, cells, holes, v.coarse_shape, rank, iterations, 1)
        lines.append(f"view {n}: coarse {v.coarse_shape}, {cells} cells, {holes} holes, plan {plan}, {cost.passes} passes, {cost.bytes_read} bytes read, {cost.bytes_shuffled} bytes shuffled a task")
    return "\n".join(lines)
