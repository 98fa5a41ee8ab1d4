"""Cost models: operations, passes, bytes and memory, from sizes only."""

from __future__ import annotations

from dataclasses import dataclass

from finegrain.operators.kernels import FACTOR_BYTES

Shape = tuple[int, int, int]


def flop_model(shape: Shape, coarse_t: Shape, coarse_c: Shape, rank: int, cells_t: int | None = None, cells_c: int | None = None) -> dict[str, int]:
    """Multiplications of one gradient of the first block: products of factor rows, residuals, sums, and spreading to members.

    With cells_t and cells_c (stored cells), of a pass that reads stored cells only; else of complete views.
    """
    nt = cells_t if cells_t is not None else coarse_t[0] * coarse_t[1] * coarse_t[2]
    nc = cells_c if cells_c is not None else coarse_c[0] * coarse_c[1] * coarse_c[2]
    out = {
        "rows_t": coarse_t[1] * coarse_t[2] * rank, "rows_c": coarse_c[1] * coarse_c[2] * rank,
        "residual": (nt + nc) * rank, "mask": nt + nc, "sums": (nt + nc) * rank, "spread": shape[0] * rank,
    }
    return out | {"total": sum(out.values())}


def dominant(shape: Shape, periods: int, iu: int, jv: int, rank: int) -> int:
    """The order of one gradient: n_i * n_j * periods * R + iu * jv * n_k * R."""
    return shape[0] * shape[1] * periods * rank + iu * jv * shape[2] * rank


def memory_model(shape: Shape, coarse_t: Shape, coarse_c: Shape, rank: int) -> dict[str, int]:
    """Bytes that each method must hold at once: in one process with operator matrices, and in the engine."""
    n = shape[0] * shape[1] * shape[2]
    views = coarse_t[0] * coarse_t[1] * coarse_t[2] + coarse_c[0] * coarse_c[1] * coarse_c[2]
    return {
        "least_squares_matrix": 8 * views * n,
        "least_squares_block": 8 * 6 * shape[0] * shape[2] * max(1, -(-shape[1] // coarse_c[1])),
        "factors": 8 * rank * sum(shape),
        "views": 32 * views,
        "fine_cube": 32 * n,
    }


@dataclass(frozen=True)
class PassCost:
    passes: int
    cells: int
    bytes_read: int
    bytes_shuffled: int


def fit_cost(plan: str, cells: int, holes: int, shape: Shape, rank: int, iterations: int, tasks: int, bytes_per_cell: int = 12) -> PassCost:
    """A coupled fit's passes over one view: two for each block of an observed view, one where Gram matrices stand for absent
    cells (and two over the holes, if any)."""
    blocks = 3 * iterations
    passes = blocks * {"observed": 2, "gram": 1, "complement": 1}[plan]
    read = passes * cells + (2 * blocks * holes if plan == "complement" else 0)
    return PassCost(passes, read, read * bytes_per_cell, passes * tasks * max(shape) * rank * 8)


def placement(shape: Shape, rank: int, limit: int = FACTOR_BYTES) -> dict[str, str]:
    """Which factors are broadcast: all, while they fit in the limit; else the largest modes must be partitioned (split the cube
    along them into ranges and fit these with shared factors)."""
    size = {m: 8 * n * rank for m, n in zip("ijk", shape)}
    out = dict.fromkeys("ijk", "broadcast")
    for m in sorted(size, key=size.get, reverse=True):
        if sum(size[x] for x in "ijk" if out[x] == "broadcast") <= limit:
            break
        out[m] = "partitioned"
    return out
