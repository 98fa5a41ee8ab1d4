"""Coupled factorisation of the views' time unfoldings: a row factor P for each (i, j), a time factor Q.

P has as many rows as the cube has (i, j) pairs, so it stays distributed. Rows are packed once by contemporaneous group: all
that the update of P needs (its rows' temporal cells, the group's row of the contemporaneous view) lies together, so an
iteration shuffles nothing but partial sums of Q's size.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain import shared
from finegrain.operators.groupings import Grouping
from finegrain.operators.held import HELD_CELLS, HeldCubes
from finegrain.operators.kernels import solve_rows
from finegrain.operators.metrics import nde_pieces
from finegrain.operators.views import View, held_views

#: A packed row's bytes, most of them temporal cells; larger groups are refused before anything runs.
GROUP_BYTES = 1 << 30
GRID = (1, 2, 5, 10, 15, 25, 40)
PACKED = "gi long, gj long, i array<long>, j array<long>, weight array<double>, t array<double>, c array<double>, p array<double>"


class MatrixFit:
    def __init__(self, rows: DataFrame, q: np.ndarray, losses: list[float], seconds: float):
        self.rows, self.q, self.losses, self.seconds = rows, q, losses, seconds

    @property
    def rank(self) -> int:
        return self.q.shape[1]

    def cells(self) -> DataFrame:
        """i, j, k, v of all fine cells of the rows that the views have."""
        q = self.q

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for r in batch.to_pylist():
                    p = np.array(r["p"]).reshape(-1, q.shape[1])
                    n, k = len(p), len(q)
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(r["i"], k)), pa.array(np.repeat(r["j"], k)), pa.array(np.tile(np.arange(k), n)), pa.array((p @ q.T).ravel())], names=["i", "j", "k", "v"])

        return self.rows.select("i", "j", "p").mapInArrow(run, "i long, j long, k long, v double")


def _placed(g: Grouping | None, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The group of each member (-1: none) and its weight there."""
    if g is None:
        return np.arange(n), np.ones(n)
    if len(np.unique(g.member)) != len(g.member):
        raise ValueError("groups that overlap can't be packed by group")
    group, weight = np.full(n, -1, np.int64), np.zeros(n)
    group[g.member], weight[g.member] = g.grp, g.weight
    return group, weight


def packed_rows(view_t: View, view_c: View) -> DataFrame:
    """A row for each group (gi, gj): its members' temporal cells (NaN where missing) and its contemporaneous row."""
    n_i, n_j, _ = view_t.shape
    u, v, w = view_c.groupings.get("i"), view_c.groupings.get("j"), view_t.groupings["k"]
    for g in (u, v):
        if g is not None and len(np.unique(g.member)) != len(g.member):
            raise ValueError("groups that overlap can't be packed by group")
    members = [int(g.sizes().max(initial=0)) if g is not None else 1 for g in (u, v)]
    if 8 * members[0] * members[1] * (w.n_groups + 4) > GROUP_BYTES:
        raise ValueError(f"a group of {members[0] * members[1]} rows of {w.n_groups} periods is more than a packed row should hold ({GROUP_BYTES} bytes)")
    spark = view_t.cells.sparkSession
    table = lambda g, n, m: spark.createDataFrame(pa.table({m: g.member if g else np.arange(n), f"g{m}": g.grp if g else np.arange(n), f"w{m}": g.weight if g else np.ones(n)}))
    t = view_t.cells.join(F.broadcast(table(u, n_i, "i")), "i").join(F.broadcast(table(v, n_j, "j")), "j")
    t = t.select("gi", "gj", F.lit(0).alias("side"), "i", "j", (F.col("wi") * F.col("wj")).alias("weight"), "k", "v")
    none = F.lit(None).cast("long")
    c = view_c.cells.select(F.col("i").alias("gi"), F.col("j").alias("gj"), F.lit(1).alias("side"), none.alias("i"), none.alias("j"), F.lit(None).cast("double").alias("weight"), "k", "v")
    fill = 0.0 if view_t.absent == "zero" else np.nan
    fill_c = 0.0 if view_c.absent == "zero" else np.nan

    def pack(table: pa.Table) -> pa.Table:
        a = table.column("side").to_numpy() == 0
        k, value = table.column("k").to_numpy(), table.column("v").to_numpy()
        if a.any():
            i, j = (table.column(x).to_numpy()[a].astype(np.int64) for x in "ij")
            keys, where = np.unique(np.stack([i, j], 1), axis=0, return_inverse=True)
            t_rows = np.full((len(keys), w.n_groups), fill)
            t_rows[where.ravel(), k[a]] = value[a]
            weight = np.zeros(len(keys))
            weight[where.ravel()] = table.column("weight").to_numpy()[a]
        else:
            keys, t_rows, weight = np.zeros((0, 2), np.int64), np.zeros((0, w.n_groups)), np.zeros(0)
        c_row = np.full(w.n_members, fill_c)
        c_row[k[~a]] = value[~a]
        row = {"gi": table.column("gi")[0].as_py(), "gj": table.column("gj")[0].as_py(), "i": keys[:, 0], "j": keys[:, 1], "weight": weight, "t": t_rows.ravel(), "c": c_row, "p": np.zeros(0)}
        return pa.Table.from_pylist([row], schema=_arrow())

    return t.unionByName(c).where("v IS NOT NULL").groupBy("gi", "gj").applyInArrow(pack, PACKED)


def _arrow() -> pa.Schema:
    many = lambda t: pa.list_(t)
    return pa.schema([("gi", pa.int64()), ("gj", pa.int64()), ("i", many(pa.int64())), ("j", many(pa.int64())), ("weight", many(pa.float64())), ("t", many(pa.float64())), ("c", many(pa.float64())), ("p", many(pa.float64()))])


class Row:
    """A packed row as arrays, with its residuals."""

    def __init__(self, r: dict, rank: int, periods: int):
        self.raw = r
        self.weight = np.array(r["weight"])
        self.t = np.array(r["t"]).reshape(-1, periods)
        self.c = np.array(r["c"])
        self.p = np.array(r["p"]).reshape(-1, rank) if len(r["p"]) else np.zeros((len(self.weight), rank))

    def residuals(self, p: np.ndarray, q: np.ndarray, wq: np.ndarray, data: float = 1.0) -> tuple[np.ndarray, np.ndarray]:
        """Model minus data (or the model alone), zero where missing."""
        et = np.where(np.isnan(self.t), 0.0, p @ wq.T - data * np.nan_to_num(self.t))
        ec = np.where(np.isnan(self.c), 0.0, (self.weight @ p) @ q.T - data * np.nan_to_num(self.c))
        return et, ec

    def gradient(self, q: np.ndarray, wq: np.ndarray) -> np.ndarray:
        et, ec = self.residuals(self.p, q, wq)
        return 2 * (et @ wq + np.outer(self.weight, ec @ q))


def _sums(rows: DataFrame, f, width: int, rank: int, periods: int) -> np.ndarray:
    """The sum over packed rows of an array of ``width`` numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(width)
        for batch in batches:
            for r in batch.to_pylist():
                total += f(Row(r, rank, periods))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(width)), pa.array(total)], names=["n", "x"])

    got = rows.mapInArrow(run, "n long, x double").groupBy("n").agg(F.sum("x").alias("x")).toArrow()
    out = np.zeros(width)
    out[got.column("n").to_numpy()] = got.column("x").to_numpy()
    return out


def _updated(rows: DataFrame, f, rank: int, periods: int) -> DataFrame:
    """The packed rows with a new p, written: a pass reads it several times."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [r | {"p": f(Row(r, rank, periods)).ravel()} for r in batch.to_pylist()]
            yield pa.RecordBatch.from_pylist(out, schema=_arrow())

    return shared.table(rows.mapInArrow(run, PACKED))


class HeldRows:
    """All packed rows of a cube as arrays: members below each other, and where each group begins. seen: where cells aren't missing."""

    def __init__(self, sizes: np.ndarray, weight: np.ndarray, t: np.ndarray, seen_t: np.ndarray, c: np.ndarray, seen_c: np.ndarray):
        self.group, self.n = np.repeat(np.arange(len(sizes)), sizes), len(sizes)
        begins = np.cumsum(sizes) - sizes
        self.filled, self.begins, self.weight = np.flatnonzero(sizes), begins[sizes > 0], weight[:, None]
        self.t, self.seen_t, self.c, self.seen_c = t, seen_t, c, seen_c

    @staticmethod
    def of(rows: list[dict], periods: int) -> HeldRows:
        whole = lambda name: np.concatenate([np.array(r[name], float) for r in rows])
        t, c = whole("t").reshape(-1, periods), np.array([r["c"] for r in rows], float)
        return HeldRows(np.array([len(r["i"]) for r in rows], np.int64), whole("weight"), np.nan_to_num(t), ~np.isnan(t), np.nan_to_num(c), ~np.isnan(c))

    @staticmethod
    def packed(view_t: View, view_c: View) -> tuple[HeldRows, np.ndarray, np.ndarray]:
        """The rows of held views as ``packed_rows`` has them, and the first and second index of each."""
        t, c = view_t.cells, view_c.cells
        (gi, wi), (gj, wj) = (_placed(view_c.groupings.get(m), n) for m, n in zip("ij", view_t.shape))
        i, j = np.nonzero(t.seen.any(2) & (gi >= 0)[:, None] & (gj >= 0))
        group = gi[i] * c.values.shape[1] + gj[j]
        order = np.argsort(group, kind="stable")
        i, j = i[order], j[order]
        sizes, has = np.bincount(group, minlength=int(np.prod(c.values.shape[:2]))), c.seen.any(2).ravel()
        own = np.flatnonzero((sizes > 0) | has)
        seen = lambda view, x: x if view.absent == "missing" else np.ones_like(x)
        sides = (v.reshape(-1, v.shape[2])[own] for v in (c.values, seen(view_c, c.seen)))
        return HeldRows(sizes[own], wi[i] * wj[j], t.values[i, j], seen(view_t, t.seen[i, j]), *sides), i, j

    def grouped(self, p: np.ndarray) -> np.ndarray:
        out = np.zeros((self.n, p.shape[1]))
        if len(self.filled):
            out[self.filled] = np.add.reduceat(self.weight * p, self.begins)
        return out

    def residuals(self, p: np.ndarray, q: np.ndarray, wq: np.ndarray, data: float = 1.0) -> tuple[np.ndarray, np.ndarray]:
        return (p @ wq.T - data * self.t) * self.seen_t, (self.grouped(p) @ q.T - data * self.c) * self.seen_c


def held_steps(h: HeldRows, w: Grouping, rank: int, max_iter: int, nonneg: bool = False) -> tuple[np.ndarray, np.ndarray, list[float]]:
    """The steps of ``fit_coupled_matrix`` on rows in this process: p, q and losses."""
    n_k, periods = w.n_members, w.n_groups
    square = lambda *e: sum(float(np.vdot(x, x)) for x in e)
    values, vectors = np.linalg.eigh(h.c.T @ h.c)
    q = vectors[:, np.argsort(-values)[:rank]] * np.sqrt(n_k)
    if nonneg:
        q = np.abs(q)
    wq = w.apply(q)
    ridge = wq.T @ wq + (1e-6 if rank <= periods else 1e-2) * np.trace(wq.T @ wq) / rank * np.eye(rank)
    p, losses = solve_rows(ridge, h.t @ wq), []
    for _ in range(max_iter):
        wq = w.apply(q)
        et, ec = h.residuals(p, q, wq)
        d = 2 * (et @ wq + h.weight * (ec @ q)[h.group])
        below = square(*h.residuals(d, q, wq, data=0.0))
        p = p - (0.5 * square(d) / below if below > 0 else 0.0) * d
        if nonneg:
            p = np.maximum(p, 0)
        et, ec = h.residuals(p, q, wq)
        d = 2 * (w.back(et.T @ p) + ec.T @ h.grouped(p))
        below, top = square(*h.residuals(p, d, w.apply(d), data=0.0)), 0.5 * square(d)
        q = q - (top / below if below > 0 else 0.0) * d
        if nonneg:
            q = np.maximum(q, 0)
        losses.append(square(et, ec) - (top**2 / below if below > 0 else 0.0))
    return p, q, losses


def held_matrix(view_t: View, view_c: View, rank: int, max_iter: int = 10) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The estimate of ``fit_coupled_matrix`` from held views, in pieces of a first-mode index each."""
    w = view_t.groupings["k"]
    h, i, j = HeldRows.packed(view_t, view_c)
    if not h.n:
        return
    p, q, _ = held_steps(h, w, min(rank, w.n_members), max_iter)
    order = np.argsort(i, kind="stable")
    for rows in np.split(order, np.flatnonzero(np.diff(i[order])) + 1) if len(i) else []:
        yield i[rows[:1]], j[rows], (p[rows] @ q.T)[None]


def held_fit(rows: DataFrame, w: Grouping, rank: int, max_iter: int, nonneg: bool) -> tuple[DataFrame, np.ndarray, list[float]]:
    """The steps of ``fit_coupled_matrix`` for a cube that one task holds: packed rows with their p (written), q and losses."""
    n_k, periods = w.n_members, w.n_groups
    schema = _arrow().append(pa.field("q", pa.list_(pa.float64()))).append(pa.field("losses", pa.list_(pa.float64())))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packed = [r for batch in batches for r in batch.to_pylist()]
        if not packed:
            return
        h = HeldRows.of(packed, periods)
        p, q, losses = held_steps(h, w, rank, max_iter, nonneg)
        ends = np.searchsorted(h.group, np.arange(h.n + 1))
        for at in range(0, len(packed), 1000):
            own = [r | {"p": p[ends[n] : ends[n + 1]].ravel(), "q": q.ravel() if n == 0 else None, "losses": losses if n == 0 else None} for n, r in enumerate(packed[at : at + 1000], at)]
            yield pa.RecordBatch.from_pylist(own, schema=schema)

    out = shared.table(rows.coalesce(1).mapInArrow(run, PACKED + ", q array<double>, losses array<double>"))
    found = out.where("q IS NOT NULL").select("q", "losses").first()
    q, losses = (np.array(found[0]).reshape(n_k, rank), list(found[1])) if found else (np.zeros((n_k, rank)), [0.0] * max_iter)
    return out.drop("q", "losses"), q, losses


def fit_coupled_matrix(view_t: View, view_c: View, rank: int, max_iter: int = 10, nonneg: bool = False, rows: DataFrame | None = None) -> MatrixFit:
    """Alternating exact steps from a start by the eigenvectors of the contemporaneous unfolding's Gram matrix (missing: zero)."""
    began = time.perf_counter()
    w = view_t.groupings["k"]
    n_k, periods = w.n_members, w.n_groups
    rank = min(rank, n_k)
    rows = rows if rows is not None else shared.table(packed_rows(view_t, view_c))
    if int(np.prod(view_t.shape)) <= HELD_CELLS:
        rows, q, losses = held_fit(rows, w, rank, max_iter, nonneg)
        return MatrixFit(rows, q, losses, time.perf_counter() - began)
    g = _sums(rows, lambda r: np.outer(np.nan_to_num(r.c), np.nan_to_num(r.c)).ravel(), n_k * n_k, rank, periods).reshape(n_k, n_k)
    values, vectors = np.linalg.eigh(g)
    q = vectors[:, np.argsort(-values)[:rank]] * np.sqrt(n_k)
    if nonneg:
        q = np.abs(q)
    wq = w.apply(q)
    ridge = wq.T @ wq + (1e-6 if rank <= periods else 1e-2) * np.trace(wq.T @ wq) / rank * np.eye(rank)
    rows = _updated(rows, lambda r: solve_rows(ridge, np.nan_to_num(r.t) @ wq), rank, periods)
    losses = []
    for _ in range(max_iter):
        wq = w.apply(q)

        def first(r: Row, q=q, wq=wq) -> np.ndarray:
            d = r.gradient(q, wq)
            dt, dc = r.residuals(d, q, wq, data=0.0)
            return np.array([(d**2).sum(), (dt**2).sum() + (dc**2).sum()])

        top, below = _sums(rows, first, 2, rank, periods)
        step = 0.5 * top / below if below > 0 else 0.0

        def moved(r: Row, q=q, wq=wq, step=step) -> np.ndarray:
            p = r.p - step * r.gradient(q, wq)
            return np.maximum(p, 0) if nonneg else p

        rows = _updated(rows, moved, rank, periods)

        def second(r: Row, q=q, wq=wq) -> np.ndarray:
            et, ec = r.residuals(r.p, q, wq)
            return np.concatenate([(et.T @ r.p).ravel(), np.outer(ec, r.weight @ r.p).ravel(), [(et**2).sum() + (ec**2).sum()]])

        s = _sums(rows, second, periods * rank + n_k * rank + 1, rank, periods)
        d = 2 * (w.back(s[: periods * rank].reshape(periods, rank)) + s[periods * rank : -1].reshape(n_k, rank))
        wd = w.apply(d)

        def third(r: Row, d=d, wd=wd) -> np.ndarray:
            dt, dc = r.residuals(r.p, d, wd, data=0.0)
            return np.array([(dt**2).sum() + (dc**2).sum()])

        below = _sums(rows, third, 1, rank, periods)[0]
        top = 0.5 * (d**2).sum()
        q = q - (top / below if below > 0 else 0.0) * d
        if nonneg:
            q = np.maximum(q, 0)
        losses.append(float(s[-1] - (top**2 / below if below > 0 else 0.0)))
    return MatrixFit(rows, q, losses, time.perf_counter() - began)


def best_rank(view_t: View, view_c: View, score: Callable[[DataFrame], float] | HeldCubes, ranks: tuple[int, ...] = GRID, max_iter: int = 10) -> tuple[MatrixFit | None, dict[int, float]]:
    """The fit with the least ``score(cells)`` over the feasible ranks of a grid; views are packed once.

    Where ``score`` is the views and the true cube as HeldCubes, each rank is a task that returns its error, and no fit is kept.
    """
    most = min(view_t.groupings["k"].n_members, view_t.shape[0] * view_t.shape[1])
    tried = [r for r in ranks if r <= most]
    if isinstance(score, HeldCubes):
        own = held_views(view_t, view_c)
        errors = score.run([lambda t, c, x, r=r: nde_pieces(x, held_matrix(*own(t, c), r, max_iter)) for r in tried])
        return None, {r: error for r, (error, _) in zip(tried, errors, strict=True)}
    rows = shared.table(packed_rows(view_t, view_c))

    def one(r: int) -> tuple[MatrixFit, float]:
        fit = fit_coupled_matrix(view_t, view_c, r, max_iter, rows=rows)
        return fit, score(fit.cells())

    done = dict(zip(tried, shared.together([lambda r=r: one(r) for r in tried]), strict=True))
    fits, scores = {r: f for r, (f, _) in done.items()}, {r: x for r, (_, x) in done.items()}
    return fits[min(scores, key=scores.get)], scores
