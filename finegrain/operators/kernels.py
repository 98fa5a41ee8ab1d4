"""Passes over a view's cells, shared by all iterative methods.

A pass gathers factor rows by index, forms products over modes in Arrow batches, and adds up one row for each coarse
index it meets: task-local sums first, then an aggregation by index. What crosses to the driver is a coarse factor's size.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.operators.held import HeldCells
from finegrain.operators.views import View

#: Factors up to this many bytes in all are broadcast. Larger ones are refused: see ``plans.planner.placement``.
FACTOR_BYTES = 256 << 20


@dataclass
class Sums:
    """What a pass adds up: a row of R sums for each index of the mode, squares, and cells read."""

    rows: np.ndarray
    squares: float = 0.0
    cells: int = 0


def check_size(factors: dict[str, np.ndarray]) -> None:
    size = sum(f.nbytes for f in factors.values())
    if size > FACTOR_BYTES:
        raise ValueError(f"factors of {size} bytes exceed the {FACTOR_BYTES} that are broadcast")


@dataclass
class Pass:
    """A pass over cells: for each index of ``mode`` the sum over its cells of e times the product of the other modes' factor rows.

    values: e is model minus value ("residual"), the value ("raw"), or the model ("model", for cells without values).
    """

    cells: DataFrame
    coarse: dict[str, np.ndarray]
    mode: str
    values: str = "residual"


def tagged(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, pa.RecordBatch]]:
    """Batches of one pass each; Spark may put partitions of a union together."""
    for batch in batches:
        tags = batch.column("pass").to_numpy()
        for tag in np.unique(tags).tolist():
            yield tag, batch if (tags == tag).all() else batch.filter(pa.array(tags == tag))


def cell_passes(passes: list[Pass]) -> list[Sums]:
    """Several passes (of one rank, over cells of the same modes) as one job, over their cells tagged by pass."""
    if not passes:
        return []
    if isinstance(passes[0].cells, HeldCells):
        return [Sums(*p.cells.sums(p.coarse, p.mode, p.values), p.cells.count) for p in passes]
    for p in passes:
        check_size(p.coarse)
    modes, rank = list(passes[0].coarse), next(iter(passes[0].coarse.values())).shape[1]
    sc = passes[0].cells.sparkSession.sparkContext
    shared = sc.broadcast([(p.coarse, p.mode, p.values) for p in passes])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for tag, batch in tagged(batches):
            f, mode, values = shared.value[tag]
            n = len(f[mode])
            own = held.setdefault(tag, [np.zeros((n, rank)), np.zeros(n, bool), 0.0, 0])
            at = {m: batch.column(m).to_numpy() for m in modes}
            others = reduce(np.multiply, [f[m][at[m]] for m in modes if m != mode])
            if values == "raw":
                e = batch.column("v").to_numpy()
            else:
                e = np.einsum("nr,nr->n", others, f[mode][at[mode]])
                if values == "residual":
                    e = e - batch.column("v").to_numpy()
            for r in range(rank):
                own[0][:, r] += np.bincount(at[mode], e * others[:, r], n)
            own[1][at[mode]] = True
            own[2] += float(e @ e)
            own[3] += batch.num_rows
        for tag, (sums, touched, squares, seen) in held.items():
            where = np.flatnonzero(touched)
            zeros = np.zeros(len(where))
            columns = [np.full(len(where) + 1, tag, np.int32), np.append(where, -1), *(np.append(sums[where, r], 0.0) for r in range(rank)), np.append(zeros, squares), np.append(zeros, seen).astype(np.int64)]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["pass", "idx", *rows, "squares", "seen"])

    rows = [f"g{r}" for r in range(rank)]
    frames = [p.cells.select(F.lit(n).alias("pass"), *modes, (F.lit(0.0) if p.values == "model" else F.col("v")).alias("v")) for n, p in enumerate(passes)]
    partial = reduce(DataFrame.unionByName, frames).mapInArrow(run, "pass int, idx long, " + ", ".join(f"{g} double" for g in rows) + ", squares double, seen long")
    got = partial.groupBy("pass", "idx").agg(*(F.sum(c).alias(c) for c in [*rows, "squares", "seen"])).toArrow()
    shared.destroy()  # of the driver too: a fit broadcasts its factors for every pass
    tags, index, squares, seen = (got.column(c).to_numpy() for c in ("pass", "idx", "squares", "seen"))
    table = np.stack([got.column(g).to_numpy() for g in rows], 1)
    out = []
    for n, p in enumerate(passes):
        mine, whole = (tags == n) & (index >= 0), (tags == n) & (index < 0)
        sums = np.zeros((len(p.coarse[p.mode]), rank))
        sums[index[mine]] = table[mine]
        out.append(Sums(sums, float(squares[whole].sum()), int(seen[whole].sum())))
    return out


def cell_pass(cells: DataFrame, coarse: dict[str, np.ndarray], mode: str, values: str = "residual") -> Sums:
    """One pass; squares is the sum of e squared."""
    return cell_passes([Pass(cells, coarse, mode, values)])[0]


def direction_squares(cells: DataFrame, coarse: dict[str, np.ndarray], mode: str, direction: np.ndarray) -> float:
    """The sum over cells of the squared model with ``direction`` in place of the mode's factor."""
    return cell_pass(cells.select(*coarse), coarse | {mode: direction}, mode, "model").squares


def expression_pass(cells: DataFrame, coarse: dict[str, DataFrame], mode: str, rank: int, values: str = "residual") -> DataFrame:
    """As cell_pass, for small ranks, as one plan in generated code: idx, g0..gR-1. coarse: idx, f for each mode."""
    out = cells
    for m, f in coarse.items():
        out = out.join(F.broadcast(f.select(F.col("idx").alias(m), F.col("f").alias(f"f_{m}"))), m)
    product = lambda ms, r: reduce(lambda a, b: a * b, [F.col(f"f_{m}")[r] for m in ms])
    others = [m for m in coarse if m != mode]
    model = reduce(lambda a, b: a + b, [product(coarse, r) for r in range(rank)])
    e = {"raw": F.col("v"), "residual": model - F.col("v"), "model": model}[values]
    return out.groupBy(F.col(mode).alias("idx")).agg(*(F.sum(e * product(others, r)).alias(f"g{r}") for r in range(rank)))


def gram(factor: np.ndarray) -> np.ndarray:
    return factor.T @ factor


def others_gram(coarse: dict[str, np.ndarray], mode: str) -> np.ndarray:
    return reduce(np.multiply, [gram(f) for m, f in coarse.items() if m != mode])


def solve_rows(g: np.ndarray, rhs: np.ndarray) -> np.ndarray:
    """rhs times the inverse of the symmetric g; a ridge relative to its trace where it is nearly singular."""
    ridge = 1e-10 * max(np.trace(g), 1e-300) * np.eye(len(g))
    return np.linalg.solve(g + ridge, rhs.T).T


def value_squares(view: View) -> tuple[float, int]:
    """Sum of squared values and their number."""
    if isinstance(view.cells, HeldCells):
        return view.cells.squares, view.cells.count
    row = view.cells.agg(F.coalesce(F.sum(F.col("v") * F.col("v")), F.lit(0.0)), F.count("v")).first()
    return float(row[0]), int(row[1])


@dataclass
class BlockSums:
    """What a view contributes to one block's update: half the gradient in coarse rows, and the loss."""

    half: np.ndarray
    loss: float
    cells: int


class ViewKernel:
    """A view and its residual plan.

    observed: absent cells are missing; two passes for each block (gradient, then the step's denominator).
    gram: absent cells are zeros; Gram matrices stand for all cells, so a pass reads stored rows only, and once for each block.
    complement: as gram, less what the listed holes would add; for views with few holes.
    """

    def __init__(self, view: View, names: dict[str, str] | None = None):
        self.view, self.names = view, names or {m: m for m in view.modes}
        self.plan = "observed" if view.absent == "missing" else "gram" if view.holes is None else "complement"
        self.squares = value_squares(view)[0] if self.plan != "observed" else 0.0
        self.passes = 0

    def coarse(self, factors: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
        return self.view.coarse({m: factors[n] for m, n in self.names.items()})

    def mode_of(self, name: str) -> str | None:
        return next((m for m, n in self.names.items() if n == name), None)

    def block(self, factors: dict[str, np.ndarray], mode: str) -> BlockSums:
        return blocks([(self, mode)], factors)[0]

    def block_passes(self, factors: dict[str, np.ndarray], mode: str) -> list[Pass]:
        """What a block's update reads of this view."""
        f = self.coarse(factors)
        own = [Pass(self.view.cells, f, mode, "residual" if self.plan == "observed" else "raw")]
        return own + ([Pass(self.view.holes, f, mode, "model")] if self.plan == "complement" else [])

    def block_of(self, factors: dict[str, np.ndarray], mode: str, sums: list[Sums]) -> BlockSums:
        self.passes += len(sums)
        s = sums[0]
        if self.plan == "observed":
            return BlockSums(s.rows, s.squares, s.cells)
        f = self.coarse(factors)
        g = others_gram(f, mode)
        half = f[mode] @ g - s.rows
        loss = float((gram(f[mode]) * g).sum()) - 2 * float((f[mode] * s.rows).sum()) + self.squares
        for h in sums[1:]:
            half, loss = half - h.rows, loss - h.squares
        return BlockSums(half, max(loss, 0.0), s.cells)

    def raw(self, factors: dict[str, np.ndarray], mode: str) -> np.ndarray:
        """Values times the other modes' factors, for least squares: missing cells count as zeros."""
        self.passes += 1
        return cell_pass(self.view.cells, self.coarse(factors), mode, "raw").rows

    def denominator(self, factors: dict[str, np.ndarray], mode: str, direction: np.ndarray) -> float:
        """Squared norm of the model with a (coarse) direction in one block, over the view's observed cells."""
        return self.denominator_of(factors, mode, direction, cell_passes(self.denominator_passes(factors, mode, direction)))

    def denominator_passes(self, factors: dict[str, np.ndarray], mode: str, direction: np.ndarray) -> list[Pass]:
        """What that reads of this view: nothing where Gram matrices stand for all cells."""
        if self.plan == "gram":
            return []
        cells = self.view.cells if self.plan == "observed" else self.view.holes
        return [Pass(cells, self.coarse(factors) | {mode: direction}, mode, "model")]

    def denominator_of(self, factors: dict[str, np.ndarray], mode: str, direction: np.ndarray, sums: list[Sums]) -> float:
        self.passes += len(sums)
        if self.plan == "observed":
            return sums[0].squares
        out = float((gram(direction) * others_gram(self.coarse(factors), mode)).sum())
        return max(out - sum(s.squares for s in sums), 0.0)

    def loss(self, factors: dict[str, np.ndarray]) -> float:
        return self.block(factors, self.view.modes[0]).loss


def blocks(members: list[tuple[ViewKernel, str]], factors: dict[str, np.ndarray]) -> list[BlockSums]:
    """The block sums of several views, each with the mode that the block is in it, in one job."""
    wanted = [k.block_passes(factors, mode) for k, mode in members]
    sums = iter(cell_passes([p for w in wanted for p in w]))
    return [k.block_of(factors, mode, [next(sums) for _ in w]) for (k, mode), w in zip(members, wanted, strict=True)]


def denominators(members: list[tuple[ViewKernel, str, np.ndarray]], factors: dict[str, np.ndarray]) -> list[float]:
    """The denominators of several views, each with the block's mode and coarse direction, in one job (or none)."""
    wanted = [k.denominator_passes(factors, mode, d) for k, mode, d in members]
    sums = iter(cell_passes([p for w in wanted for p in w]))
    return [k.denominator_of(factors, mode, d, [next(sums) for _ in w]) for (k, mode, d), w in zip(members, wanted, strict=True)]
