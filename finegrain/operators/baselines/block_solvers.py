"""Least squares on series: minimum norm, smooth, and sparse in the cosine basis.

Neither view adds up cells of different contemporaneous groups, so the problem falls apart by pair of first- and second-mode
group (an ungrouped mode: by index). Each part is one task's dense problem of members x members x ticks unknowns. Without missing cells it is solved at once by
the eigenvectors of its modes, else by conjugate gradients from zero (which stays in the row space, so the solution has minimum norm); no operator matrix of a
part's size is ever formed.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.operators.groupings import Grouping
from finegrain.operators.views import View

#: What a task may hold for one part; a larger part is refused before anything runs.
BLOCK_BYTES = 4 << 30
LAMBDAS = (0.01, 0.1, 1.0, 10.0)


def dct_basis(n: int) -> np.ndarray:
    """The orthonormal cosine basis of type II: row m is frequency m."""
    m, k = np.arange(n)[:, None], np.arange(n)[None, :]
    return np.cos(np.pi * m * (2 * k + 1) / (2 * n)) * np.where(m == 0, np.sqrt(1 / n), np.sqrt(2 / n))


@dataclass
class Block:
    """Data of one part: temporal cells (n_i, members, periods) and contemporaneous cells (groups, ticks), with masks."""

    u: Grouping | None
    w: Grouping
    share: np.ndarray  # weight of each member in the second-mode group
    yt: np.ndarray
    mt: np.ndarray
    yc: np.ndarray
    mc: np.ndarray
    known: dict = field(default_factory=dict)  # spectra of earlier parts

    def temporal(self, x: np.ndarray) -> np.ndarray:
        return np.moveaxis(self.w.apply(np.moveaxis(x, 2, 0)), 0, 2)

    def temporal_back(self, y: np.ndarray) -> np.ndarray:
        return np.moveaxis(self.w.back(np.moveaxis(y, 2, 0)), 0, 2)

    def contemporaneous(self, x: np.ndarray) -> np.ndarray:
        s = np.einsum("ijk,j->ik", x, self.share)
        return self.u.apply(s) if self.u else s

    def contemporaneous_back(self, y: np.ndarray) -> np.ndarray:
        s = self.u.back(y) if self.u else y
        return s[:, None, :] * self.share[None, :, None]

    def normal(self, x: np.ndarray) -> np.ndarray:
        return self.temporal_back(self.mt * self.temporal(x)) + self.contemporaneous_back(self.mc * self.contemporaneous(x))

    def right(self) -> np.ndarray:
        return self.temporal_back(self.mt * self.yt) + self.contemporaneous_back(self.mc * self.yc)


class Spectrum:
    """The normal operator of a part without missing cells, plus ``smooth`` times the squared differences and ``ridge``, as eigenvalues.

    The temporal view acts on ticks only and the contemporaneous one on members only, so eigenvectors of three small matrices solve it at once.
    """

    def __init__(self, b: Block, smooth: float, ridge: float):
        n_i, _, n_k = b.yt.shape[0], b.yt.shape[1], b.w.n_members
        dense = lambda g: g.apply(np.eye(g.n_members))
        u, w, d = dense(b.u) if b.u else np.eye(n_i), dense(b.w), np.diff(np.eye(n_k), axis=0)
        (di, self.i), (dj, self.j), (dk, self.k) = (np.linalg.eigh(m) for m in (u.T @ u, np.outer(b.share, b.share), w.T @ w + smooth * d.T @ d + ridge * np.eye(n_k)))
        values = np.outer(di, dj)[:, :, None] + dk
        self.inverse = np.where(values > 1e-10 * values.max(), 1 / np.where(values == 0, 1.0, values), 0.0)

    def solve(self, right: np.ndarray) -> np.ndarray:
        """The solution of least norm."""
        turn = lambda x, i, j, k: np.tensordot(i, j @ (x @ k), 1)
        return turn(self.inverse * turn(right, self.i.T, self.j.T, self.k), self.i, self.j, self.k.T)


def spectrum(b: Block, smooth: float, ridge: float = 0.0) -> Spectrum | None:
    """That of a part, made once for all parts alike; none where cells are missing."""
    if not (b.mt.all() and b.mc.all()):
        return None
    key = (b.yt.shape, b.share.tobytes(), smooth, ridge, *((b.u.member.tobytes(), b.u.grp.tobytes(), b.u.weight.tobytes()) if b.u else ()))
    if key not in b.known:
        b.known[key] = Spectrum(b, smooth, ridge)
    return b.known[key]


def smoothness(x: np.ndarray) -> np.ndarray:
    """Gradient (half) of the squared differences of neighbouring ticks."""
    d = np.diff(x, axis=2)
    out = np.zeros_like(x)
    out[:, :, :-1] -= d
    out[:, :, 1:] += d
    return out


def conjugate_gradients(operator: Callable[[np.ndarray], np.ndarray], right: np.ndarray, tol: float = 1e-10, most: int = 2000, start: np.ndarray | None = None) -> np.ndarray:
    x = np.zeros_like(right) if start is None else start.copy()
    r = right - operator(x) if start is not None else right.copy()
    p, rr = r.copy(), float((r * r).sum())
    goal = tol**2 * float((right * right).sum())
    for _ in range(most):
        if rr <= goal:
            break
        ap = operator(p)
        below = float((p * ap).sum())
        if below <= 0:
            break
        a = rr / below
        x += a * p
        r -= a * ap
        new = float((r * r).sum())
        p = r + new / rr * p
        rr = new
    return x


def solve_smooth(b: Block, lam: float) -> np.ndarray:
    """Least squares with lam times the squared differences; lam = 0 is the minimum-norm solution."""
    if (direct := spectrum(b, lam)) is not None:
        return direct.solve(b.right())
    return conjugate_gradients(lambda x: b.normal(x) + lam * smoothness(x), b.right())


def solve_sparse(b: Block, sparse: float, smooth: float, nonneg: bool = True, iterations: int = 60, rho: float = 1.0) -> np.ndarray:
    """Series that are sparse in the cosine basis, smooth and not negative, by alternating directions."""
    basis, right = dct_basis(b.w.n_members), b.right()
    start = spectrum(b, 2 * smooth)
    x = start.solve(right) if start else conjugate_gradients(lambda y: b.normal(y) + 2 * smooth * smoothness(y), right, most=200)
    s, u1 = x @ basis.T, np.zeros_like(x)
    z, u2 = np.maximum(x, 0) if nonneg else x, np.zeros_like(x)
    both = 2 if nonneg else 1
    direct = spectrum(b, 2 * smooth, both * rho)
    for _ in range(iterations):
        want = right + rho * (s - u1) @ basis + (rho * (z - u2) if nonneg else 0)
        x = direct.solve(want) if direct else conjugate_gradients(lambda y: b.normal(y) + 2 * smooth * smoothness(y) + both * rho * y, want, tol=1e-8, most=100, start=x)
        c = x @ basis.T
        s = np.sign(c + u1) * np.maximum(np.abs(c + u1) - sparse / rho, 0)
        u1 += c - s
        if nonneg:
            z = np.maximum(x + u2, 0)
            u2 += x - z
    return z if nonneg else x


class Members:
    """Members and weights of each group, looked up by group."""

    def __init__(self, g: Grouping):
        order = np.argsort(g.grp, kind="stable")
        self.member, self.weight = g.member[order], g.weight[order]
        self.start = np.searchsorted(g.grp[order], np.arange(g.n_groups + 1))

    def of(self, group: int) -> tuple[np.ndarray, np.ndarray]:
        s = slice(int(self.start[group]), int(self.start[group + 1]))
        order = np.argsort(self.member[s])
        return self.member[s][order], self.weight[s][order]


class Parts:
    """How two views fall apart, and the solver of a part. method: min_norm, smooth or sparse.

    First-mode groups that overlap or leave members out make parts of the whole first mode. Parts beyond BLOCK_BYTES are refused.
    It travels with tasks, so it keeps nothing of the views' cells.
    """

    def __init__(self, view_t: View, view_c: View, method: str = "min_norm", lam: float = 1.0, sparse: float = 1.0, nonneg: bool = True, iterations: int = 60):
        if method not in ("min_norm", "smooth", "sparse"):
            raise ValueError(f"method is min_norm, smooth or sparse, not {method!r}")
        self.method, self.lam, self.sparse, self.nonneg, self.iterations = method, lam, sparse, nonneg, iterations
        self.n_i, n_j, _ = view_t.shape
        self.u, self.w = view_c.groupings.get("i") or Grouping.of(np.arange(self.n_i)), view_t.groupings["k"]
        self.v = view_c.groupings.get("j") or Grouping.of(np.arange(n_j))
        if len(np.unique(self.v.member)) != len(self.v.member):
            raise ValueError("second-mode groups that overlap don't fall apart into blocks")
        self.apart = self.u.is_partition()
        largest = (int(self.u.sizes().max(initial=0)) if self.apart else self.n_i) * int(self.v.sizes().max(initial=0)) * self.w.n_members
        if 48 * largest > BLOCK_BYTES:  # the solvers hold six arrays of a part's fine cells
            raise ValueError(f"a part of {largest} fine cells is more than one task should hold ({BLOCK_BYTES} bytes): finer groups are needed, or first-mode groups that partition the mode")
        self.first, self.second = Members(self.u) if self.apart else None, Members(self.v)
        self.full_t, self.full_c = float(view_t.absent == "zero"), float(view_c.absent == "zero")
        self.known: dict = {}  # filled in the task

    @property
    def counts(self) -> tuple[int, int]:
        return self.u.n_groups if self.apart else 1, self.v.n_groups

    def members(self, pi: int, pj: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, Grouping]:
        """A part's first-mode and second-mode indexes, the weights of the latter, and its own first-mode grouping."""
        columns, share = self.second.of(pj)
        if not self.apart:
            return np.arange(self.n_i), columns, share, self.u
        rows, weight = self.first.of(pi)
        return rows, columns, share, Grouping(np.arange(len(rows)), np.zeros(len(rows), np.int64), weight, len(rows), 1)

    def solve(self, own: Grouping, share: np.ndarray, yt: np.ndarray, mt: np.ndarray, yc: np.ndarray, mc: np.ndarray) -> np.ndarray:
        b = Block(own, self.w, share, yt, mt, yc, mc, self.known)
        return solve_sparse(b, self.sparse, self.lam, self.nonneg, self.iterations) if self.method == "sparse" else solve_smooth(b, self.lam if self.method == "smooth" else 0.0)


def ls_blocks(view_t: View, view_c: View, method: str = "min_norm", lam: float = 1.0, sparse: float = 1.0, nonneg: bool = True, iterations: int = 60) -> DataFrame:
    """i, j, k, v of all fine cells of the parts that have data: see ``Parts``."""
    parts, spark = Parts(view_t, view_c, method, lam, sparse, nonneg, iterations), view_t.cells.sparkSession
    u, v, w, apart = parts.u, parts.v, parts.w, parts.apart
    t = view_t.cells.join(F.broadcast(spark.createDataFrame(pa.table({"j": v.member, "pj": v.grp}))), "j")
    if apart:
        t = t.join(F.broadcast(spark.createDataFrame(pa.table({"i": u.member, "pi": u.grp}))), "i")
    zero = F.lit(0).cast("long")
    t = t.select("pi" if apart else zero.alias("pi"), "pj", F.lit(0).alias("side"), "i", "j", "k", "v")
    c = view_c.cells.select(F.col("i").alias("pi") if apart else zero.alias("pi"), F.col("j").alias("pj"), F.lit(1).alias("side"), "i", F.lit(-1).cast("long").alias("j"), "k", "v")

    def solve(table: pa.Table) -> pa.Table:
        rows, columns, share, own = parts.members(table.column("pi")[0].as_py(), table.column("pj")[0].as_py())
        side, i, j, k = (table.column(x).to_numpy() for x in ("side", "i", "j", "k"))
        value = table.column("v").to_numpy()
        yt, mt = np.zeros((len(rows), len(columns), w.n_groups)), np.full((len(rows), len(columns), w.n_groups), parts.full_t)
        yc, mc = np.zeros((own.n_groups, w.n_members)), np.full((own.n_groups, w.n_members), parts.full_c)
        a = side == 0
        at = (np.searchsorted(rows, i[a]), np.searchsorted(columns, j[a]), k[a])
        yt[at], mt[at] = value[a], 1.0
        at = (np.zeros(int((~a).sum()), np.int64) if apart else i[~a], k[~a])
        yc[at], mc[at] = value[~a], 1.0
        x = parts.solve(own, share, yt, mt, yc, mc)
        cells = np.indices(x.shape).reshape(3, -1)
        return pa.table({"i": rows[cells[0]], "j": columns[cells[1]], "k": cells[2], "v": x.ravel()})

    return t.unionByName(c).where("v IS NOT NULL").groupBy("pi", "pj").applyInArrow(solve, "i long, j long, k long, v double")


def held_blocks(view_t: View, view_c: View, method: str = "min_norm", lam: float = 1.0, slice_: tuple[int, int] = (0, 1)) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray | None]]:
    """As ``ls_blocks`` of held views, part by part: first and second indexes, and the solution. slice_: (n, of), only each of-th part is solved."""
    parts, t, c = Parts(view_t, view_c, method, lam), view_t.cells, view_c.cells
    for n, (pi, pj) in enumerate(np.ndindex(*parts.counts)):
        rows, columns, share, own = parts.members(pi, pj)
        if n % slice_[1] != slice_[0]:
            yield rows, columns, None
            continue
        at, group = np.ix_(rows, columns), slice(pi, pi + 1) if parts.apart else slice(None)
        mt, mc = t.seen[at], c.seen[group, pj]
        x = parts.solve(own, share, t.values[at], np.maximum(mt, parts.full_t), c.values[group, pj], np.maximum(mc, parts.full_c)) if mt.any() or mc.any() else 0.0
        yield rows, columns, x


def min_norm_ls(view_t: View, view_c: View) -> DataFrame:
    return ls_blocks(view_t, view_c)


def smooth_ls(view_t: View, view_c: View, lam: float = 1.0) -> DataFrame:
    return ls_blocks(view_t, view_c, "smooth", lam)


def dct_sparse(view_t: View, view_c: View, lam1: float = 1.0, lam2: float = 0.1, nonneg: bool = True, max_iter: int = 60) -> DataFrame:
    return ls_blocks(view_t, view_c, "sparse", lam2, lam1, nonneg, max_iter)
