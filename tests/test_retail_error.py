"""Errors that the fits of the given retail cube report: those of the same methods written densely, from another start and from the same one.

On sf0.1, where the literal in the queries' SQL (the error on sf0.01) doesn't hold.
"""

import duckdb
import numpy as np
import pytest
from dense import matrix, model, observe

from finegrain import catalog
from finegrain.operators import groupings as G
from finegrain.operators import metrics
from finegrain.operators.blind import fit_blind
from finegrain.operators.coupled import fit_coupled
from finegrain.plans import workloads as W

SF = "/root/testdata/sf0.1"
OTHERS = ("ijk,jr,kr->ir", "ijk,ir,kr->jr", "ijk,ir,jr->kr")


def products(y, factors, n):
    return np.einsum(OTHERS[n], y, *(f for m, f in enumerate(factors) if m != n), optimize=True)


def solved(y, factors, n):
    """One factor by least squares, given the others."""
    whole = np.prod([f.T @ f for m, f in enumerate(factors) if m != n], axis=0)
    return products(y, factors, n) @ np.linalg.pinv(whole)


def decomposed(y, rank, rounds=10):
    rng = np.random.default_rng(1)
    factors = [rng.random((n, rank)) for n in y.shape]
    for _ in range(rounds):
        for n in range(3):
            factors[n] = solved(y, factors, n)
    return factors


def descended(views, factors, order, mu=0.0, rounds=10):
    """Best steps along the gradient, block by block. A view: values, names of its modes' factors, matrices that group them."""
    sign = {"k": 1.0, "kt": -1.0} if mu else {}
    for _ in range(rounds):
        for name in order:
            gradient = np.zeros_like(factors[name])
            having = [(y, names.index(name), [m @ factors[x] for m, x in zip(maps, names)], maps) for y, names, maps in views if name in names]
            for y, n, f, maps in having:
                gradient += 2 * maps[n].T @ products(model(*f) - y, f, n)
            if name in sign:
                gradient += 2 * mu * sign[name] * (factors["k"].sum(0) - factors["kt"].sum(0))
            below = sum((model(*(maps[n] @ gradient if m == n else x for m, x in enumerate(f))) ** 2).sum() for _, n, f, maps in having)
            below += mu * (gradient.sum(0) ** 2).sum() if name in sign else 0.0
            factors[name] = factors[name] - 0.5 * (gradient**2).sum() / below * gradient
        if not mu:
            norms = {x: np.linalg.norm(f, axis=0) for x, f in factors.items()}
            even = np.prod(list(norms.values()), axis=0) ** (1 / 3)
            factors = {x: f / norms[x] * even for x, f in factors.items()}
    return factors


@pytest.fixture(scope="module")
def retail(spark):
    """The cube, its two views and their groupings as matrices."""
    con = duckdb.connect()
    for t in ("lineitem", "supplier", "part"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    found = con.sql(catalog.NBW).fetchnumpy()
    x = np.zeros(catalog.NBW_SHAPE)
    x[found["i"], found["j"], found["k"]] = found["v"]
    u, w = W.regions(spark, SF), G.period(357, 4)
    return x, observe(x, w=w), observe(x, u=u), matrix(u), matrix(w)


def error(x, factors):
    return ((x - model(factors["i"], factors["j"], factors["k"])) ** 2).sum() / (x**2).sum()


def test_blind_retail(spark, retail):
    x, yt, yc, _, w = retail
    it, j, k = decomposed(yc, 10)
    start = {"it": it, "j": j, "k": k, "kt": w @ k, "i": solved(yt, [np.zeros((25, 10)), j, w @ k], 0)}
    whole = [np.eye(n) for n in yt.shape], [np.eye(n) for n in yc.shape]
    own = error(x, descended([(yt, ("i", "j", "kt"), whole[0]), (yc, ("it", "j", "k"), whole[1])], start, ("i", "it", "j", "k", "kt"), mu=100.0))
    assert catalog.QUERIES["blind_retail"](spark, SF).first().own_nde == round(own, 2)


def test_coupled_retail(spark, retail):
    x, yt, yc, u, w = retail
    _, j, k = decomposed(yc, 10)
    start = {"j": j, "k": k, "i": solved(yt, [np.zeros((25, 10)), j, w @ k], 0)}
    maps = [np.eye(25), np.eye(25), w], [u, np.eye(25), np.eye(357)]
    own = error(x, descended([(yt, ("i", "j", "k"), maps[0]), (yc, ("i", "j", "k"), maps[1])], start, ("i", "j", "k")))
    assert catalog.QUERIES["coupled_retail"](spark, SF).first().own_nde == round(own, 2)


def decomposed_from_own_start(y, rank, rounds=10):
    """With the fits' own random start, and columns of equal norms after each round as they have them."""
    rng = np.random.default_rng(0)
    factors = [rng.random((n, rank)) + 0.1 for n in y.shape]
    for _ in range(rounds):
        for n in range(3):
            factors[n] = solved(y, factors, n)
        norms = [np.linalg.norm(f, axis=0) for f in factors]
        factors = [f / m * np.prod(norms, axis=0) ** (1 / 3) for f, m in zip(factors, norms)]
    return factors


def spark_error(spark, fit_views):
    t, c = (v.placed() for v in catalog.nbw_views(spark, SF, absent="zero"))
    truth = catalog.densify(W.retail_nbw(spark, SF), dict(zip("ijk", catalog.NBW_SHAPE)))
    return metrics.nde_model(truth, fit_views(t, c).factors)


def test_blind_from_the_same_start(spark, retail):
    """To the digits of the fit, not only to two. Its start guesses equal periods, as it isn't told the real ones."""
    x, yt, yc, _, _ = retail
    it, j, k = decomposed_from_own_start(yc, 10)
    kt = matrix(G.chunk(357, 90)) @ k
    start = {"it": it, "j": j, "k": k, "kt": kt, "i": solved(yt, [np.zeros((25, 10)), j, kt], 0)}
    whole = [np.eye(n) for n in yt.shape], [np.eye(n) for n in yc.shape]
    own = error(x, descended([(yt, ("i", "j", "kt"), whole[0]), (yc, ("it", "j", "k"), whole[1])], start, ("i", "it", "j", "k", "kt"), mu=100.0))
    assert spark_error(spark, lambda t, c: fit_blind(t, c, 10)) == pytest.approx(own, abs=1e-6)


def test_coupled_from_the_same_start(spark, retail):
    x, yt, yc, u, w = retail
    _, j, k = decomposed_from_own_start(yc, 10)
    start = {"j": j, "k": k, "i": solved(yt, [np.zeros((25, 10)), j, w @ k], 0)}
    maps = [np.eye(25), np.eye(25), w], [u, np.eye(25), np.eye(357)]
    own = error(x, descended([(yt, ("i", "j", "k"), maps[0]), (yc, ("i", "j", "k"), maps[1])], start, ("i", "j", "k")))
    assert spark_error(spark, lambda t, c: fit_coupled([t, c], 10, placed=True)) == pytest.approx(own, abs=1e-6)
