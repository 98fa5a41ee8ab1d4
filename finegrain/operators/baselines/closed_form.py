"""Estimators in closed form: plain aggregations and joins, nothing iterative.

Every view is looked up on the one frame of keys, group by group: the frame is never joined with itself, and coarse views that Spark finds small
enough are broadcast, so that the fine cells need not move at all.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from finegrain.operators.groupings import Grouping
from finegrain.operators.views import View


def with_groups(keys: DataFrame, groupings: dict[str, Grouping | None], tag: str = "") -> DataFrame:
    """keys with the group ``i_g, j_g, k_g`` of each index and the total weight ``i_n, j_n, k_n`` of that group (names begin with ``tag``).

    An index in several groups gets a row for each, one in none a row without group.
    """
    out, spark = keys, keys.sparkSession
    for m in "ijk":
        g = groupings.get(m)
        if g is None:
            out = out.withColumn(f"{tag}{m}_g", F.col(m)).withColumn(f"{tag}{m}_n", F.lit(1.0))
            continue
        total = np.bincount(g.grp, g.weight, g.n_groups)
        table = spark.createDataFrame(pa.table({m: g.member, f"{tag}{m}_g": g.grp, f"{tag}{m}_n": total[g.grp]}))
        out = out.join(F.broadcast(table), m, "left")
    return out


def _parted(view: View) -> bool:
    return all(g is None or g.is_partition() for g in view.groupings.values())


def looked_up(keys: DataFrame, view: View, name: str) -> DataFrame:
    """keys' columns and ``name``: the view's cell over each key, divided by what it adds up; null where there is none.

    Where periods overlap, a key has a row for each group that holds it.
    """
    own = [f"{name}{m}_g" for m in "ijk"]
    cells = view.cells.select(*(F.col(m).alias(g) for m, g in zip("ijk", own)), F.col("v").alias(f"{name}_v"))
    placed = with_groups(keys, view.groupings, name).join(cells, own, "left")
    value: Column = F.col(f"{name}_v")
    if view.absent == "zero":
        value = F.when(F.col(own[0]).isNotNull() & F.col(own[1]).isNotNull() & F.col(own[2]).isNotNull(), F.coalesce(value, F.lit(0.0)))
    size = F.col(f"{name}i_n") * F.col(f"{name}j_n") * F.col(f"{name}k_n")
    return placed.select(*keys.columns, (value / size).alias(name))


def spread(keys: DataFrame, view: View, name: str) -> DataFrame:
    """keys (i, j, k) with the view's cell over them, divided by what it adds up; null where there is none.

    Where periods overlap, the mean over the groups that hold the key.
    """
    each = looked_up(keys.select("i", "j", "k"), view, name)
    return each if _parted(view) else each.groupBy("i", "j", "k").agg(F.avg(name).alias(name))


def mean_split(keys: DataFrame, view_t: View, view_c: View) -> DataFrame:
    """i, j, k, v: the mean of both views' even shares; one share where the other view has no cell, null where neither has."""
    # A view whose groups overlap comes first, as its rows have to be put together by key.
    first, second = (view_c, view_t) if _parted(view_t) else (view_t, view_c)
    both = spread(keys, first, "_a")
    both = looked_up(both, second, "_b") if _parted(second) else both.join(spread(keys, second, "_b"), ["i", "j", "k"])
    return both.select("i", "j", "k", F.when(F.col("_a").isNotNull() & F.col("_b").isNotNull(), (F.col("_a") + F.col("_b")) / 2).otherwise(F.coalesce("_a", "_b")).alias("v"))


class Shares:
    """The even shares of a held view, a series for each second-mode index: as ``spread``, null is NaN."""

    def __init__(self, view: View):
        self.view = view
        groupings = [view.groupings.get(m) or Grouping.of(np.arange(n)) for m, n in zip("ijk", view.shape)]
        self.totals = [np.bincount(g.grp, g.weight, g.n_groups) for g in groupings]
        self.unit = [replace(g, weight=np.ones(len(g.member))) for g in groupings]
        order = np.argsort(groupings[0].member, kind="stable")
        self.groups, self.starts = groupings[0].grp[order], np.searchsorted(groupings[0].member[order], np.arange(view.shape[0] + 1))

    def of(self, i: int) -> np.ndarray:
        cells, size = self.view.cells, np.outer(*self.totals[1:])
        total, n = np.zeros(size.shape), np.zeros(size.shape)
        for g in self.groups[self.starts[i] : self.starts[i + 1]].tolist():
            total += cells.values[g] / (self.totals[0][g] * size)
            n += cells.seen[g] if self.view.absent == "missing" else 1.0
        total, n = (self.unit[2].back(self.unit[1].back(x).T).T for x in (total, n))
        return np.where(n > 0, total / np.maximum(n, 1), np.nan)


def held_mean_split(view_t: View, view_c: View) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """As ``mean_split`` of held views, in pieces of a first-mode index each; zero where neither view has a share."""
    sides, every = [Shares(v) for v in (view_t, view_c)], np.arange(view_t.shape[1])
    for i in range(view_t.shape[0]):
        a, b = (s.of(i) for s in sides)
        mean = np.where(np.isnan(a), b, np.where(np.isnan(b), a, (a + b) / 2))
        yield np.array([i]), every, np.nan_to_num(mean)[None]


def min_norm_closed(keys: DataFrame, view_t: View, view_c: View) -> DataFrame:
    """Least squares of minimum norm for complete, consistent views with groups that partition their modes.

    A cell is its share of the contemporaneous cell, plus its share of the temporal cell, less the mean share of the block of
    group and period. The block is the contemporaneous view added up over periods: a view like the others.
    """
    for v in (view_t, view_c):
        if not _parted(v) or v.holes is not None:
            raise ValueError("the closed form needs complete views whose groups partition the modes; use ls_blocks")
    w = replace(view_t.groupings["k"], weight=np.ones(len(view_t.groupings["k"].member)))
    ticks = keys.sparkSession.createDataFrame(pa.table({"k": w.member, "w": w.grp}))
    block = view_c.cells.join(F.broadcast(ticks), "k").groupBy("i", "j", F.col("w").alias("k")).agg(F.sum("v").alias("v"))
    views = {"_t": view_t, "_c": view_c, "_b": replace(view_c, cells=block, groupings=view_c.groupings | {"k": w})}
    out = keys.select("i", "j", "k")
    for name, v in views.items():
        out = looked_up(out, replace(v, absent="zero"), name)
    return out.select("i", "j", "k", (F.col("_t") + F.col("_c") - F.col("_b")).alias("v"))
