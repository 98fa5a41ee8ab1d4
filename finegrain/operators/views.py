"""Coarse views of a cube: mode products with groupings, one shuffle for each view."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.operators.groupings import Grouping
from finegrain.operators.held import HeldCells

#: A grouping table up to this many bytes is broadcast; a larger one is joined by shuffle.
BROADCAST_BYTES = 64 << 20


@dataclass(frozen=True)
class View:
    """Observed cells of a coarse cube in coarse indexes, and the grouping of each mode (None: not grouped).

    absent: what a cell without a row is, "missing" or "zero". With "zero", ``holes`` may list cells (i, j, k) that
    are missing nevertheless. shape: sizes of the fine modes, whose columns are the letters of ``modes`` (three, or more).
    """

    cells: DataFrame
    shape: tuple[int, ...]
    groupings: dict[str, Grouping | None]
    absent: str = "missing"
    holes: DataFrame | None = None
    weight: float = 1.0
    modes: str = "ijk"

    @property
    def coarse_shape(self) -> tuple[int, ...]:
        return tuple(g.n_groups if (g := self.groupings.get(m)) else n for m, n in zip(self.modes, self.shape))

    def coarse(self, factors: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
        """Factors with this view's groupings applied: the data are never spread to fine cells."""
        return {m: g.apply(f) if (g := self.groupings.get(m)) else f for m, f in factors.items()}

    def placed(self) -> View:
        """The view's cells written to the shared folder once, for the many passes of a fit."""
        if isinstance(self.cells, HeldCells):
            return self
        from finegrain import shared  # here, as views travel with tasks and sessions can't

        return replace(self, cells=shared.table(self.cells.select(*self.modes, "v").where("v IS NOT NULL")), holes=None if self.holes is None else shared.table(self.holes.select(*self.modes)))


def held_views(*views: View) -> Callable[..., tuple[View, ...]]:
    """What makes these views from their cells where those are held; it travels with a task, as it keeps no frame."""
    sides = [(v.shape, v.groupings, v.absent, v.weight) for v in views]
    return lambda *cells: tuple(View(x, shape, groupings, absent, None, weight) for x, (shape, groupings, absent, weight) in zip(cells, sides, strict=True))


def _joined(cells: DataFrame, mode: str, grouping: Grouping) -> tuple[DataFrame, str, str]:
    table = grouping.frame(cells.sparkSession)
    table = table.withColumnsRenamed({"member": mode, "grp": f"{mode}_grp", "weight": f"{mode}_weight"})
    if 24 * len(grouping.member) <= BROADCAST_BYTES:
        table = F.broadcast(table)
    return cells.join(table, mode), f"{mode}_grp", f"{mode}_weight"


def mode_products(cells: DataFrame, groupings: dict[str, Grouping | None], missing_rule: str = "any") -> DataFrame:
    """Cells aggregated by the groupings of all given modes in one group-by.

    missing_rule: "any", a coarse cell exists if one of its atoms is observed; "all", only if all are;
    "zero", missing atoms count as zeros (the same cells as "any": what no atom reaches stays absent).
    """
    if missing_rule not in ("any", "all", "zero"):
        raise ValueError(f"missing_rule is any, all or zero, not {missing_rule!r}")
    out, keys, weight = cells.where("v IS NOT NULL"), [], F.lit(1.0)
    atoms = 1
    sizes = []
    for mode in [c for c in cells.columns if c != "v"]:
        g = groupings.get(mode)
        if g is None:
            keys.append(F.col(mode))
            continue
        out, grp, w = _joined(out, mode, g)
        keys.append(F.col(grp).alias(mode))
        weight = weight * F.col(w)
        sizes.append((mode, g))
    summed = out.groupBy(*keys).agg(F.sum(F.col("v") * weight).alias("v"), F.count("*").alias("_atoms"))
    if missing_rule == "all":
        spark = cells.sparkSession
        for mode, g in sizes:
            rows = [(n, int(c)) for n, c in enumerate(g.sizes())]
            summed = summed.join(F.broadcast(spark.createDataFrame(rows, f"{mode} long, {mode}_size long")), mode)
            atoms = atoms * F.col(f"{mode}_size")
        summed = summed.where(F.col("_atoms") == atoms) if sizes else summed
    return summed.select(*[c for c in cells.columns if c != "v"], "v")


def mode_product(cells: DataFrame, mode: str, grouping: Grouping, missing_rule: str = "any") -> DataFrame:
    return mode_products(cells, {mode: grouping}, missing_rule)


def make_view(cells: DataFrame, shape: tuple[int, ...], missing_rule: str = "any", absent: str = "missing", weight: float = 1.0, modes: str = "ijk", **groupings: Grouping | None) -> View:
    """A view of the cube: ``make_view(cells, shape, i=U, j=V)``."""
    for m, g in groupings.items():
        if g is not None and g.n_members != shape[modes.index(m)]:
            raise ValueError(f"the grouping of mode {m} has {g.n_members} members, the cube {shape[modes.index(m)]}")
    return View(mode_products(inside(cells, shape, modes), groupings, missing_rule), shape, dict(groupings), absent, None, weight, modes)


def inside(cells: DataFrame, shape: tuple[int, ...], modes: str = "ijk") -> DataFrame:
    """cells, of which none may have an index outside the cube: its row would vanish in a join or spoil a sum, so it is an error."""
    outside = reduce(lambda a, b: a | b, ((F.col(m) < 0) | (F.col(m) >= n) for m, n in zip(modes, shape)))
    said = F.concat(F.lit(f"a cell outside the cube {shape}: "), F.concat_ws(", ", *(F.col(m).cast("string") for m in modes)))
    return cells.where(F.when(outside, F.raise_error(said).cast("boolean")).otherwise(F.lit(True)))


def temporal_view(cells: DataFrame, shape: tuple[int, int, int], grouping: Grouping, missing_rule: str = "any", absent: str = "missing") -> View:
    """Summed over the periods of the time mode."""
    return make_view(cells, shape, missing_rule, absent, k=grouping)


def contemporaneous_view(cells: DataFrame, shape: tuple[int, int, int], first: Grouping, second: Grouping | None = None, missing_rule: str = "any", absent: str = "missing") -> View:
    """Summed over groups of the first mode, and of the second if given (one shuffle either way)."""
    return make_view(cells, shape, missing_rule, absent, i=first, j=second)


def coarser(view: View, **groupings: Grouping) -> View:
    """A coarser view from a finer one (sums of sums), so that a ladder of levels reads the cube once.

    groupings are of the view's own coarse indexes.
    """
    cells = mode_products(view.cells, groupings)
    composed = dict(view.groupings)
    for m, outer in groupings.items():
        inner = composed.get(m)
        if inner is None:
            composed[m] = outer
            continue
        steps: dict[tuple[int, int], float] = {}
        up: dict[int, list[tuple[int, float]]] = {}
        for mid, grp, w in zip(outer.member.tolist(), outer.grp.tolist(), outer.weight.tolist(), strict=True):
            up.setdefault(mid, []).append((grp, w))
        for member, mid, w in zip(inner.member.tolist(), inner.grp.tolist(), inner.weight.tolist(), strict=True):
            for grp, w2 in up.get(mid, []):
                steps[member, grp] = steps.get((member, grp), 0.0) + w * w2
        keys = np.array(list(steps), np.int64).reshape(-1, 2)
        composed[m] = Grouping(keys[:, 0], keys[:, 1], np.array(list(steps.values())), inner.n_members, outer.n_groups)
    return replace(view, cells=cells, groupings=composed)


def masked(view: View, keep: DataFrame) -> View:
    """The view with only the cells for which ``keep`` (i, j, k) has a row; absent cells are missing from now on."""
    return replace(view, cells=view.cells.join(keep.select("i", "j", "k"), ["i", "j", "k"], "left_semi"), absent="missing", holes=None)
