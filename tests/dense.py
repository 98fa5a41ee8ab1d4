"""Dense reference forms, for tests only."""

import numpy as np


def matrix(g):
    """A grouping as a dense matrix."""
    out = np.zeros((g.n_groups, g.n_members))
    np.add.at(out, (g.grp, g.member), g.weight)
    return out


def observe(x, u=None, v=None, w=None):
    for axis, g in enumerate((u, v, w)):
        if g is not None:
            x = np.moveaxis(np.tensordot(matrix(g), x, (1, axis)), 0, axis)
    return x


def model(a, b, c):
    return np.einsum("ir,jr,kr->ijk", a, b, c)


def loss(factors, views):
    """views: (values with NaN, {mode: grouping})."""
    total = 0.0
    for y, groups in views:
        f = [matrix(groups[m]) @ factors[m] if groups.get(m) is not None else factors[m] for m in "ijk"]
        total += np.nansum((model(*f) - y) ** 2)
    return total


def numeric_gradient(f, x, step=1e-5):
    out = np.zeros_like(x)
    for at in np.ndindex(x.shape):
        d = np.zeros_like(x)
        d[at] = step
        out[at] = (f(x + d) - f(x - d)) / (2 * step)
    return out
