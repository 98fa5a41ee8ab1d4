"""Cubes on the given tables, and the experiment workloads on them."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from finegrain import shared
from finegrain.operators import groupings as G
from finegrain.operators.baselines.block_solvers import LAMBDAS, Parts, held_blocks, ls_blocks
from finegrain.operators.baselines.closed_form import held_mean_split, mean_split
from finegrain.operators.baselines.coupled_matrix import GRID, best_rank
from finegrain.operators.blind import MU, fit_blind
from finegrain.operators.coupled import Fit, fit_coupled
from finegrain.operators.cpd import als, fit_cp
from finegrain.operators.cube import CubeSpec, build_cube, densify, top_items
from finegrain.operators.held import HELD_CELLS, HeldCubes
from finegrain.operators.identifiability import rank_bound, ranks_for
from finegrain.operators.metrics import nde_model, nde_pieces, nde_value
from finegrain.operators.reconstruct import reconstruct
from finegrain.operators.views import View, held_views, make_view, masked
from finegrain.operators.masks import mask_fiber, mask_random
from finegrain.sources.planted import SIZE, grid, planted_cube
from finegrain.sources.tables import load

METHODS = ("mean_split", "min_norm_ls", "smooth_ls", "dct_sparse", "coupled_matrix", "coupled_cp", "cp_oracle")
SCORE = "workload string, level string, method string, rank int, nde double, n_cells long, seconds double"


def months(column: str) -> F.Column:
    return (F.year(column) - 1995) * 12 + F.month(column) - 1


def brand() -> F.Column:
    """Place of p_brand (Brand#1 .. Brand#25) among its sorted strings, from its number: no dictionary is joined."""
    order = sorted((f"Brand#{n}" for n in range(1, 26)))
    number = F.regexp_extract("p_brand", "#([0-9]+)", 1).cast("int")
    return F.element_at(F.array(*(F.lit(order.index(f"Brand#{n}")) for n in range(1, 26))), number).cast("long")


def place_in(column: str, values: list[str]) -> F.Column:
    return (F.array_position(F.array(*map(F.lit, values)), F.col(column)) - 1).cast("long")


TYPES = ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"]
KINDS = ["click", "error", "purchase", "signup", "view"]
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
LANGS = ["de", "en", "es", "fr"]


def sales(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with the supplier's nation and the part's brand and type: dimensions are joined, facts are read once."""
    return load(spark, sf_dir, "lineitem").join(load(spark, sf_dir, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(load(spark, sf_dir, "part"), F.col("l_partkey") == F.col("p_partkey"))


def retail_nbw(spark: SparkSession, sf_dir: str) -> DataFrame:
    week = F.floor(F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-02").cast("date")) / 7)
    return build_cube(sales(spark, sf_dir), CubeSpec({"i": F.col("s_nationkey"), "j": brand(), "k": week}, F.col("l_quantity")))


def retail_by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nation x brand x week x type: i, j, k, r, v."""
    week = F.floor(F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-02").cast("date")) / 7)
    return build_cube(sales(spark, sf_dir), CubeSpec({"i": F.col("s_nationkey"), "j": brand(), "k": week, "r": place_in("p_type", TYPES)}, F.col("l_quantity")))


def retail_sbm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return build_cube(sales(spark, sf_dir), CubeSpec({"i": F.col("l_suppkey"), "j": brand(), "k": months("l_shipdate")}, F.col("l_quantity")))


def dept_stm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return build_cube(sales(spark, sf_dir), CubeSpec({"i": F.col("l_suppkey"), "j": place_in("p_type", TYPES), "k": months("l_shipdate")}, F.col("l_extendedprice"), "money"))


def dept_qtm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return build_cube(sales(spark, sf_dir), CubeSpec({"i": F.col("l_suppkey"), "j": place_in("p_type", TYPES), "k": months("l_shipdate")}, F.col("l_quantity")))


def mixed_ntm(spark: SparkSession, sf_dir: str) -> DataFrame:
    item = place_in("p_type", TYPES) * 25 + brand()
    return build_cube(sales(spark, sf_dir), CubeSpec({"i": F.col("s_nationkey"), "j": item, "k": months("l_shipdate")}, F.col("l_quantity")))


def category_top50(spark: SparkSession, sf_dir: str, category: str = "PROMO") -> DataFrame:
    own = sales(spark, sf_dir).where(F.col("p_type") == category)
    top = top_items(own, "p_type", "p_partkey", "l_quantity", 50).select("p_partkey", "place")
    return build_cube(own.join(F.broadcast(top), "p_partkey"), CubeSpec({"i": F.col("s_nationkey"), "j": F.col("place"), "k": months("l_shipdate")}, F.col("l_quantity")))


def orders_ncm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """customer nation x (segment, priority) x month; segments and priorities by the order of their sorted values."""
    facts = load(spark, sf_dir, "orders").join(load(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    place = lambda c: F.dense_rank().over(Window.orderBy(c)) - 1
    names = load(spark, sf_dir, "customer").select("c_mktsegment").distinct().withColumn("s", place("c_mktsegment"))
    priorities = load(spark, sf_dir, "orders").select("o_orderpriority").distinct().withColumn("p", place("o_orderpriority"))
    facts = facts.join(F.broadcast(names), "c_mktsegment").join(F.broadcast(priorities), "o_orderpriority")
    return build_cube(facts, CubeSpec({"i": F.col("c_nationkey"), "j": F.col("s") * 5 + F.col("p"), "k": months("o_orderdate")}, F.col("o_totalprice"), "money"))


def _day(column: str = "ts") -> F.Column:
    return F.datediff(F.col(column).cast("date"), F.lit("2024-01-01").cast("date"))


def incident_utd(spark: SparkSession, sf_dir: str) -> DataFrame:
    band = F.floor(F.get_json_object("props", "$.k").cast("int") / 10)
    return build_cube(load(spark, sf_dir, "events"), CubeSpec({"i": F.pmod("user_id", F.lit(150)), "j": place_in("event_type", KINDS) * 10 + band, "k": _day()}, F.lit(1), "count"))


def sensor_utd(spark: SparkSession, sf_dir: str) -> DataFrame:
    return build_cube(load(spark, sf_dir, "events"), CubeSpec({"i": F.pmod("user_id", F.lit(50)), "j": place_in("event_type", KINDS), "k": _day()}, F.col("value"), "avg"))


def embed_lsd(spark: SparkSession, sf_dir: str) -> DataFrame:
    slot = F.row_number().over(Window.partitionBy("label").orderBy("vec_id")) - 1
    rows = load(spark, sf_dir, "embeddings").withColumn("slot", slot)
    return rows.select(F.col("label").cast("long").alias("i"), F.col("slot").cast("long").alias("j"), F.posexplode("embedding").alias("k", "x")).select("i", "j", F.col("k").cast("long").alias("k"), F.col("x").cast("double").alias("v"))


def docs_sln(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    band = F.length(F.bin(F.col("n_chars") + 1)) - 1  # floor(log2(n_chars + 1)) in whole numbers
    low = docs.agg(F.min(band).alias("low"))
    source = F.regexp_extract("source", "([0-9]+)", 1).cast("long")
    return build_cube(docs.crossJoin(F.broadcast(low)), CubeSpec({"i": source, "j": place_in("lang", LANGS), "k": band - F.col("low")}, F.lit(1), "count"))


CUBES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], tuple[int, int, int]]] = {
    "retail_nbw": (retail_nbw, (25, 25, 357)), "retail_sbm": (retail_sbm, (100, 25, 83)), "category_top50": (category_top50, (25, 50, 83)),
    "mixed_ntm": (mixed_ntm, (25, 150, 83)), "dept_stm": (dept_stm, (100, 6, 83)), "dept_qtm": (dept_qtm, (100, 6, 83)), "orders_ncm": (orders_ncm, (25, 25, 80)),
    "incident_utd": (incident_utd, (150, 50, 30)), "sensor_utd": (sensor_utd, (50, 5, 30)), "embed_lsd": (embed_lsd, (10, 59, 64)), "docs_sln": (docs_sln, (20, 4, 14)),
}


def extent(cells: DataFrame, least: tuple[int, int, int] = (1, 1, 1)) -> tuple[int, int, int]:
    """Sizes that hold all indexes of a cube."""
    row = cells.agg(*(F.coalesce(F.max(m), F.lit(0)) for m in "ijk")).first()
    return tuple(max(int(x) + 1, n) for x, n in zip(row, least))


def regions(spark: SparkSession, sf_dir: str) -> G.Grouping:
    """nation -> region."""
    return G.by_column(load(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("idx"), "n_regionkey"), "n_regionkey")


def supplier_bands(spark: SparkSession, sf_dir: str, n: int) -> G.Grouping:
    """Suppliers in n bands of their account balance."""
    return G.by_ntile(load(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("idx"), "s_acctbal"), "s_acctbal", n)


@dataclass
class Level:
    """An aggregation level of a workload: how the two views group the modes."""

    name: str
    w: G.Grouping
    u: G.Grouping
    v: G.Grouping | None = None


@dataclass
class Workload:
    name: str
    cells: DataFrame
    shape: tuple[int, int, int]
    levels: list[Level]
    absent: str = "zero"
    signed: bool = False

    def views(self, level: Level) -> tuple[View, View]:
        return (make_view(self.cells, self.shape, absent=self.absent, k=level.w), make_view(self.cells, self.shape, absent=self.absent, i=level.u, j=level.v))


def _levels(shape, *levels: tuple[str, int, int | G.Grouping, int | None], how: str = "sum", offset: int = 0) -> list[Level]:
    out = []
    for name, width, u, items in levels:
        first = u if isinstance(u, G.Grouping) else G.chunk(shape[0], u)
        out.append(Level(name, G.period(shape[2], width, offset, how), first.as_how(how), G.fixed_size(shape[1], items).as_how(how) if items else None))
    return out


def workload(spark: SparkSession, sf_dir: str, name: str, offset: int = 0, absent: str = "zero") -> Workload:
    """W1..W6, W8 and W12..W14 by name; ``offset`` shifts the periods, as unknown groupings want it (W7). absent: what a cell of a given cube without a row is."""
    if name.startswith("planted"):
        rank = int(name.removeprefix("planted") or 4)
        cells, shape = planted_cube(spark, rank), SIZE
        u = regions(spark, sf_dir)
        return Workload(name, shared.table(cells), shape, _levels(shape, ("A-mod", 4, u, None), ("A-high", 12, u, None), ("B-mod", 4, u, 5), ("B-high", 12, u, 9), offset=offset))
    build, size = CUBES[name.split("/")[0]]
    if name == "dept_stm":
        size = (load(spark, sf_dir, "supplier").count(), *size[1:])  # the bands are those of all suppliers, and of no others
    cells = shared.table(build(spark, sf_dir, name.split("/")[1]) if "/" in name else build(spark, sf_dir))
    shape = extent(cells, size)
    u = regions(spark, sf_dir) if shape[0] == 25 else None
    third = -(-shape[0] // 3)
    spec = {
        "retail_nbw": [("A-mod", 4, u, None), ("A-high", 12, 3, None)],
        "category_top50": [("A-mod", 4, u, None)],
        "retail_sbm": [("A-mod", 4, max(shape[0] * 19 // 100, 1), None), ("A-high", 12, max(shape[0] // 10, 1), None)],
        "dept_stm": [("A-mod", 4, supplier_bands(spark, sf_dir, third) if name == "dept_stm" else third, None), ("A-high", 12, supplier_bands(spark, sf_dir, -(-shape[0] // 5)) if name == "dept_stm" else third, None)],
        "mixed_ntm": [("B-a", 4, u, None), ("B-b", 4, u, 10), ("B-c", 12, u, 25)],
        "incident_utd": [("B-a", 3, -(-shape[0] // 5), 5), ("B-b", 3, -(-shape[0] // 10), 10), ("B-c", 6, -(-shape[0] // 20), 20)],
        "orders_ncm": [("A-mod", 3, u, None)],
        "sensor_utd": [("A-mod", 7, 13, None), ("A-high", 15, 7, None)],
        "embed_lsd": [("A-mod", 7, 3, None)],
        "docs_sln": [("A-mod", 4, 4, None)],
    }[name.split("/")[0]]
    how = "avg" if name in ("sensor_utd", "embed_lsd") else "sum"
    return Workload(name, cells, shape, _levels(shape, *spec, how=how, offset=offset), absent, signed=how == "avg")


def run_level(w: Workload, level: Level, ranks: tuple[int, ...] | None = None, methods: tuple[str, ...] = ("mean_split", "min_norm_ls", "coupled_cp", "cp_oracle"), iterations: int = 10, seed: int = 0) -> list[tuple]:
    """Score rows (workload, level, method, rank, nde, n_cells, seconds) of one level; the views are written once.

    The weight of smooth_ls and the rank of coupled_matrix (the one reported) are the best of their grids by the error against the true cube, as
    in the published comparison: both rows are tuned by the truth. Where absent cells are missing, the oracle is fitted to the observed ones.
    A cube that a task can hold has a task for each fit, and the driver gets errors only; larger cubes are joined and fitted by distributed
    passes. Fits run side by side, and their seconds are those beside the others, of a grid's fits in all.
    """
    view_t, view_c = w.views(level)
    ranks = ranks or tuple(ranks_for(w.shape, view_c.coarse_shape, view_t.coarse_shape[2]))
    methods = tuple(m for m in methods if not (m == "dct_sparse" and w.signed or m == "blind_cp" and level.v is not None))
    score = _held_scores if int(np.prod(w.shape)) <= HELD_CELLS else _spread_scores
    n, scores = score(w, view_t, view_c, ranks, methods, iterations, seed)
    return [(w.name, level.name, method, rank, float(error), n, seconds) for method, rank, error, seconds in scores]


#: Errors of the fitted methods from (temporal view, contemporaneous view, true cells), held or not.
FITTED: dict[str, Callable[..., float]] = {
    "coupled_cp": lambda t, c, x, r, iterations, seed, absent: nde_model(x, fit_coupled([t, c], r, iterations, cp_iterations=iterations, seed=seed, placed=True).factors),
    "blind_cp": lambda t, c, x, r, iterations, seed, absent: nde_model(x, fit_blind(t, c, r, MU, iterations, iterations, seed).factors),
    "cp_oracle": lambda t, c, x, r, iterations, seed, absent: nde_model(x, fit_cp(x, t.shape, r, 2 * iterations, absent == "missing", seed).factors),
}


#: Parts of a least-squares estimate that one task solves: in closed form, and by alternating directions.
PARTS_A_TASK = (20_000, 2_000)


def _held_scores(w: Workload, view_t: View, view_c: View, ranks: tuple[int, ...], methods: tuple[str, ...], iterations: int, seed: int) -> tuple[int, list[tuple]]:
    """Cells that count, and (method, rank, error, seconds): a task for each fit."""
    import time

    cubes = HeldCubes([(view_t.cells, view_t.coarse_shape), (view_c.cells, view_c.coarse_shape), (w.cells, w.shape)], () if w.absent == "missing" else (2,))
    n = w.cells.count() if w.absent == "missing" else int(np.prod(w.shape))
    held, absent = held_views(view_t, view_c), w.absent

    def task(error: Callable[..., float]) -> Callable[..., float]:
        return lambda t, c, x: error(*held(t, c), x)

    def solved(kind: str, lam: float = 1.0) -> list[Callable[..., float]]:
        parts = int(np.prod(Parts(view_t, view_c, kind).counts))
        of = -(-parts // PARTS_A_TASK[kind == "sparse"])
        return [lambda t, c, x, n=n: nde_pieces(x, held_blocks(t, c, kind, lam, (n, of)), n == 0) for n in range(of)]

    variants: dict[str, Callable[[], list[list[Callable[..., float]]]]] = {
        "mean_split": lambda: [[lambda t, c, x: nde_pieces(x, held_mean_split(t, c))]], "min_norm_ls": lambda: [solved("min_norm")],
        "smooth_ls": lambda: [solved("smooth", lam) for lam in LAMBDAS], "dct_sparse": lambda: [solved("sparse")],
    }
    asked: list[tuple[tuple[str, int, int], Callable[..., float]]] = []  # errors of one variant add up, and the best variant counts
    for method in methods:
        if method in variants:
            asked += [((method, 0, at), task(f)) for at, fs in enumerate(variants[method]()) for f in fs]
        elif method in FITTED:
            asked += [((method, r, 0), task(lambda t, c, x, f=FITTED[method], r=r: f(t, c, x, r, iterations, seed, absent))) for r in ranks]

    def matrix() -> list[tuple[tuple[str, int, int], tuple[float, float]]]:
        began = time.perf_counter()
        scores = best_rank(view_t, view_c, cubes, GRID, iterations)[1]
        best = min(scores, key=scores.get)
        return [(("coupled_matrix", best, 0), (scores[best], time.perf_counter() - began))]

    def others() -> list[tuple[tuple[str, int, int], tuple[float, float]]]:
        return list(zip((key for key, _ in asked), cubes.run([f for _, f in asked]), strict=True))

    sums: dict[tuple[str, int, int], np.ndarray] = {}
    for rows in shared.together([others, *([matrix] if "coupled_matrix" in methods else [])]):
        for key, x in rows:
            sums[key] = sums.get(key, 0.0) + np.array(x)
    found: dict[tuple[str, int], list[np.ndarray]] = {}
    for (method, r, _), x in sums.items():
        found.setdefault((method, r), []).append(x)
    return n, [(m, r, float(min(x[0] for x in xs)), float(sum(x[1] for x in xs))) for m in methods for (of, r), xs in found.items() if of == m]


def _spread_scores(w: Workload, view_t: View, view_c: View, ranks: tuple[int, ...], methods: tuple[str, ...], iterations: int, seed: int) -> tuple[int, list[tuple]]:
    """As ``_held_scores``, by joins and passes over distributed cells."""
    import time

    view_t, view_c = view_t.placed(), view_c.placed()
    truth = shared.table(densify(w.cells, dict(zip("ijk", w.shape)), "zero") if w.absent == "zero" else w.cells)
    keys = grid(truth.sparkSession, w.shape)
    jobs: list[Callable[[], tuple]] = []

    def add(method: str, rank: int, score: Callable[[], float | tuple[int, float]]) -> None:
        def job() -> tuple:
            began = time.perf_counter()
            value = score()
            best, error = value if isinstance(value, tuple) else (rank, value)
            return method, best, error, time.perf_counter() - began

        jobs.append(job)

    def matrix() -> tuple[int, float]:
        scores = best_rank(view_t, view_c, lambda c: nde_value(truth, c), GRID, iterations)[1]
        best = min(scores, key=scores.get)
        return best, scores[best]

    for method in methods:
        if method == "mean_split":
            add(method, 0, lambda: nde_value(truth, mean_split(keys, view_t, view_c)))
        elif method == "min_norm_ls":
            add(method, 0, lambda: nde_value(truth, ls_blocks(view_t, view_c)))
        elif method == "smooth_ls":
            add(method, 0, lambda: min(nde_value(truth, ls_blocks(view_t, view_c, "smooth", lam)) for lam in LAMBDAS))
        elif method == "dct_sparse":
            add(method, 0, lambda: nde_value(truth, ls_blocks(view_t, view_c, "sparse")))
        elif method == "coupled_matrix":
            add(method, 0, matrix)
        elif method in FITTED:
            for r in ranks:
                add(method, r, lambda r=r, f=FITTED[method]: f(view_t, view_c, truth, r, iterations, seed, w.absent))
    return truth.count(), shared.together(jobs)


def run(spark: SparkSession, sf_dir: str, names: tuple[str, ...], methods: tuple[str, ...], ranks: tuple[int, ...] | None = None, iterations: int = 10, offset: int = 0) -> DataFrame:
    """Scores of all levels of some workloads."""
    rows = []
    for name in names:
        w = workload(spark, sf_dir, name, offset)
        for level in w.levels:
            rows += run_level(w, level, ranks, methods, iterations)
    return spark.createDataFrame(rows, SCORE)


def run_whole(spark: SparkSession, sf_dir: str, *names: str) -> DataFrame:
    """All methods, the ranks within the bound and 10 + 10 iterations; the blind method on periods that start 2 ticks late (W7)."""
    return run(spark, sf_dir, names, METHODS).unionByName(run(spark, sf_dir, names, ("blind_cp",), offset=2))


def run_observed(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("retail_nbw", "retail_sbm"), ranks: tuple[int, ...] = (10,), iterations: int = 10) -> DataFrame:
    """Cubes whose absent entries are missing, not zero: scored, and the oracle fitted, on the observed entries only."""
    methods = ("mean_split", "coupled_matrix", "coupled_cp", "cp_oracle", "blind_cp")
    rows = []
    for name in names:
        w = workload(spark, sf_dir, name, absent="missing")
        rows += [(f"{w.name} observed", *r[1:]) for r in run_level(w, w.levels[0], ranks, methods, iterations)]
    return spark.createDataFrame(rows, SCORE)


def missing_grid(spark: SparkSession, sf_dir: str, fractions: tuple[tuple[float, float], ...] = ((0, 0), (0.1, 0.1), (0.2, 0.2), (0.45, 0.45), (0.45, 0.1), (0.1, 0.45)), patterns: tuple[str, ...] = ("random", "fiber"), cubes: tuple[tuple[str, int], ...] = (("planted", 4), ("retail_nbw", 10)), iterations: int = 10) -> DataFrame:
    """W9: errors with missing cells, by pattern and by the shares missing in the temporal and the contemporaneous view, on a planted and a given cube."""
    import time

    jobs = []
    for name, rank in cubes:
        w = workload(spark, sf_dir, name)
        truth = shared.table(densify(w.cells, dict(zip("ijk", w.shape)), "zero"))
        whole = [v.placed() for v in w.views(w.levels[0])]
        if any(v.absent == "zero" for v in whole):  # what is masked must be missing, so all that isn't has a row
            whole = [make_view(truth, w.shape, **v.groupings).placed() for v in whole]
        for pattern in patterns:
            for f in fractions:

                def job(name=name, rank=rank, truth=truth, whole=whole, pattern=pattern, f=f) -> list[tuple]:
                    hide = (lambda c, x: mask_random(c, x)) if pattern == "random" else (lambda c, x: mask_fiber(c, "k", x))
                    t, c = (masked(v, hide(v.cells, x)).placed() for v, x in zip(whole, f))
                    level, n = f"{pattern}-{round(100 * f[0])}-{round(100 * f[1])}", int(np.prod(t.shape))
                    began = time.perf_counter()
                    mean = nde_value(truth, mean_split(grid(spark, t.shape), t, c))
                    seconds = time.perf_counter() - began
                    fit = fit_coupled([t, c], rank, iterations, cp_iterations=iterations, placed=True)
                    return [(name, level, "mean_split", 0, mean, n, seconds), (name, level, "coupled_cp", rank, nde_model(truth, fit.factors), n, fit.seconds)]

                jobs.append(job)
    return spark.createDataFrame([row for rows in shared.together(jobs) for row in rows], SCORE)


def recovery(spark: SparkSession, sf_dir: str, iterations: int = 10) -> DataFrame:
    """W8: a planted cube of rank 4 whose views keep, or miss, what exact recovery asks for: ranks below, at and above the bound, single and double
    grouping, and every fifth slab of the contemporaneous view with fewer cells than the rank."""
    w = workload(spark, sf_dir, "planted4")
    n = int(np.prod(w.shape))
    jobs = []
    for level in w.levels:
        t, c = (v.placed() for v in w.views(level))
        bound = rank_bound(*w.shape[:2], *c.coarse_shape[:2], t.coarse_shape[2])
        starved = masked(c, c.cells.where((F.pmod("k", F.lit(5)) != 0) | (F.col("i") * c.coarse_shape[1] + F.col("j") < 3))).placed()
        for regime, view, rank in (("below", c, 4), ("at", c, min(bound, 40)), ("above", c, bound + 8), ("starved", starved, 4)):

            def job(level=level, t=t, view=view, regime=regime, rank=rank) -> tuple:
                fit = fit_coupled([t, view], rank, iterations, cp_iterations=iterations, init="temporal", placed=True)
                return "planted4", f"{level.name}-{regime}", "coupled_cp", rank, nde_model(w.cells, fit.factors), n, fit.seconds

            jobs.append(job)
    return spark.createDataFrame(shared.together(jobs), SCORE)


def calendars(spark: SparkSession, sf_dir: str, rank: int = 4, iterations: int = 10) -> DataFrame:
    """W11: periods of mixed widths, with gaps, with overlaps."""
    w = workload(spark, sf_dir, "planted")
    n = w.shape[2]
    specs = {"mixed": G.mixed_calendar(n, 4, 12), "gapped": G.gapped_calendar(n, 4), "overlapping": G.overlapping_calendar(n, 8)}
    rows = []
    for name, spec in specs.items():
        level = Level(name, G.calendar(n, spec), w.levels[0].u)
        rows += run_level(w, level, (rank,), ("mean_split", "coupled_cp"), iterations)
    return spark.createDataFrame(rows, SCORE)


def ablations(spark: SparkSession, sf_dir: str, rank: int = 4, iterations: int = 5) -> DataFrame:
    """W10: start, rank, non-negativity, view weight and penalty, on the planted cube."""
    w = workload(spark, sf_dir, "planted")
    t, c = (v.placed() for v in w.views(w.levels[0]))
    fits: dict[str, Callable[[], Fit]] = {}
    more = {"cp_iterations": iterations, "placed": True}
    for init in ("auto", "bound", "random"):
        fits[f"init={init}"] = lambda init=init: fit_coupled([t, c], rank, iterations, init=init, **more)
    for r in (2, 10):
        fits[f"rank={r}"] = lambda r=r: fit_coupled([t, c], r, iterations, **more)
    fits["single view"] = lambda: fit_coupled([t], rank, iterations, start=als(t, rank, iterations).factors | {"k": chunk_spread(t, rank)}, placed=True)
    fits["nonneg"] = lambda: fit_coupled([t, c], rank, iterations, nonneg=True, **more)
    for weight in (0.5, 2.0):
        fits[f"weight={weight}"] = lambda weight=weight: fit_coupled([replace(t, weight=weight), c], rank, iterations, **more)
    for mu in (0.0, 1.0, 100.0):
        fits[f"mu={mu}"] = lambda mu=mu: fit_blind(t, c, rank, mu, iterations, iterations)

    def scored(level: str) -> tuple:
        fit = fits[level]()
        return "planted", level, "blind_cp" if "kt" in fit.factors else "coupled_cp", fit.rank, nde_model(w.cells, fit.factors), int(np.prod(w.shape)), fit.seconds

    return spark.createDataFrame(shared.together([lambda level=level: scored(level) for level in fits]), SCORE)


def chunk_spread(view: View, rank: int) -> np.ndarray:
    """A flat time factor: what one view alone says about ticks within a period."""
    w = view.groupings["k"]
    return np.ones((w.n_members, rank)) / np.maximum(w.sizes(), 1)[np.minimum(np.arange(w.n_members) // max(1, w.n_members // w.n_groups), w.n_groups - 1)][:, None]


def regional_quarters(spark: SparkSession, sf_dir: str) -> Workload:
    """W13: region x quarter from yearly regional and quarterly national sums (a cube with one second-mode index)."""
    facts = load(spark, sf_dir, "orders").join(load(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(load(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    cells = build_cube(facts, CubeSpec({"i": F.col("n_regionkey"), "j": F.lit(0), "k": F.floor(months("o_orderdate") / 3)}, F.col("o_totalprice"), "money"))
    cells = shared.table(cells)
    shape = extent(cells, (5, 1, 1))
    return Workload("regional_quarters", cells, shape, [Level("year", G.period(shape[2], 4), G.Grouping.of(np.zeros(shape[0], int)))])


def estimate_cells(w: Workload, factors: dict[str, np.ndarray]) -> DataFrame:
    return reconstruct(grid(w.cells.sparkSession, w.shape), factors)
