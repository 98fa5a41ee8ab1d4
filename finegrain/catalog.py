"""Queries over the given tables, each with SQL that says the same where SQL can."""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from finegrain.functions import sql as functions
from finegrain.operators import groupings as G
from finegrain.operators import masks, metrics
from finegrain.operators.baselines.block_solvers import ls_blocks
from finegrain.operators.baselines.closed_form import mean_split, min_norm_closed
from finegrain.operators.baselines.coupled_matrix import fit_coupled_matrix
from finegrain.operators.blind import fit_blind
from finegrain.operators.coupled import SumPenalty, coupled_loss, descend, exact_step, fit_coupled, fit_two_stage, half_gradient
from finegrain.operators.cpd import fit_cp
from finegrain.operators.cube import calendar_of, densify, dice_cube, dimension, fold, numbered, profile_cube, top_items, unfold
from finegrain.operators.identifiability import bounds_frame, rank_bound, slab_check
from finegrain.operators.kernels import ViewKernel, expression_pass, gram
from finegrain.operators.reconstruct import reconstruct, reconstruct_sql, top_cells
from finegrain.operators.views import View, coarser, make_view, mode_products
from finegrain.plans import costs, workloads as W
from finegrain.sources.planted import PlantedCubeSource, planted_cube, planted_factors
from finegrain.sources.tables import factor_frame, load
from finegrain.streaming import views as streaming

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            ORACLES[key] = sql
        return f

    return add


# --- cubes -----------------------------------------------------------------------------------------------------------

BRANDS = sorted(f"Brand#{n}" for n in range(1, 26))
SALES = "lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey"
S_BRAND = f"list_position({BRANDS}, p_brand) - 1"
S_TYPE = f"(list_position({W.TYPES}, p_type) - 1)"
S_KIND = f"(list_position({W.KINDS}, event_type) - 1)"
S_WEEK = "date_diff('day', DATE '1995-01-02', CAST(l_shipdate AS DATE)) // 7"
S_DAY = "date_diff('day', DATE '2024-01-01', CAST(ts AS DATE))"
QUANTITY = "sum(l_quantity)"


def s_month(column: str) -> str:
    return f"(year({column}) - 1995) * 12 + month({column}) - 1"


def cube(i: str, j: str, k: str, v: str, source: str) -> str:
    return f"SELECT CAST({i} AS BIGINT) AS i, CAST({j} AS BIGINT) AS j, CAST({k} AS BIGINT) AS k, CAST({v} AS DOUBLE) AS v FROM {source} GROUP BY 1, 2, 3"


CUBE_SQL = {
    "retail_nbw": cube("s_nationkey", S_BRAND, S_WEEK, QUANTITY, SALES),
    "retail_sbm": cube("l_suppkey", S_BRAND, s_month("l_shipdate"), QUANTITY, SALES),
    "dept_stm": cube("l_suppkey", S_TYPE, s_month("l_shipdate"), "sum(CAST(l_extendedprice AS DECIMAL(18, 2)))", SALES),
    "dept_qtm": cube("l_suppkey", S_TYPE, s_month("l_shipdate"), QUANTITY, SALES),
    "mixed_ntm": cube("s_nationkey", f"{S_TYPE} * 25 + {S_BRAND}", s_month("l_shipdate"), QUANTITY, SALES),
    "category_top50": cube("s_nationkey", "place", s_month("l_shipdate"), QUANTITY, f"(SELECT * FROM {SALES} WHERE p_type = 'PROMO') s JOIN (SELECT l_partkey AS top_key, row_number() OVER (ORDER BY sum(l_quantity) DESC, l_partkey) - 1 AS place FROM {SALES} WHERE p_type = 'PROMO' GROUP BY l_partkey) t ON l_partkey = top_key WHERE place < 50"),
    "orders_ncm": cube("c_nationkey", "s * 5 + p", s_month("o_orderdate"), "sum(CAST(o_totalprice AS DECIMAL(18, 2)))", "orders JOIN customer ON o_custkey = c_custkey JOIN (SELECT c_mktsegment AS sn, dense_rank() OVER (ORDER BY c_mktsegment) - 1 AS s FROM (SELECT DISTINCT c_mktsegment FROM customer)) ON sn = c_mktsegment JOIN (SELECT o_orderpriority AS pn, dense_rank() OVER (ORDER BY o_orderpriority) - 1 AS p FROM (SELECT DISTINCT o_orderpriority FROM orders)) ON pn = o_orderpriority"),
    "incident_utd": cube("user_id % 150", f"{S_KIND} * 10 + CAST(json_extract(props, '$.k') AS INT) // 10", S_DAY, "count(*)", "events"),
    "sensor_utd": cube("user_id % 50", S_KIND, S_DAY, "avg(value)", "events"),
    "embed_lsd": "SELECT CAST(label AS BIGINT) AS i, slot AS j, CAST(d AS BIGINT) AS k, CAST(embedding[d + 1] AS DOUBLE) AS v FROM (SELECT label, embedding, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS slot FROM embeddings), range(0, 64) t(d)",
    "docs_sln": cube("regexp_extract(source, '[0-9]+')", f"list_position({W.LANGS}, lang) - 1", "b - (SELECT min(length(bin(n_chars + 1)) - 1) FROM documents)", "count(*)", "(SELECT *, length(bin(n_chars + 1)) - 1 AS b FROM documents)"),
}


def cells_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return W.CUBES[name][0](spark, sf_dir)


def rounded(df: DataFrame, digits: int = 6, *names: str) -> DataFrame:
    """Doubles rounded, and no minus zero, which would hash unlike zero."""
    return df.withColumns({c: F.round(F.col(c), digits) + 0.0 for c in names or [c for c, t in df.dtypes if t == "double"]})


for _name, _sql in CUBE_SQL.items():
    query(f"SELECT i, j, k, round(v, 6) + 0.0 AS v FROM ({_sql})", f"cube_{_name}")(lambda spark, sf_dir, n=_name: rounded(cells_of(spark, sf_dir, n)))
    query(f"""
WITH c AS ({_sql}), p AS (
  SELECT count(DISTINCT i) AS n_i, count(DISTINCT j) AS n_j, count(DISTINCT k) AS n_k, count(v) AS observed, max(v) AS largest, avg(v) AS mean, stddev_pop(v) AS sd, count(*) FILTER (WHERE v = 0) AS zeros FROM c)
SELECT n_i, n_j, n_k, observed, round(largest, 4) AS largest, round(mean, 4) AS mean, round(sd, 4) AS sd, round(100 * (1 - observed / (n_i * n_j * n_k)), 4) AS missing_percent, round(100 * zeros / (n_i * n_j * n_k), 4) AS zero_percent FROM p""", f"profile_{_name}")(
        lambda spark, sf_dir, n=_name: rounded(profile_cube(cells_of(spark, sf_dir, n)), 4))


@query("SELECT CAST(row_number() OVER (ORDER BY n_name) - 1 AS BIGINT) AS idx, n_name AS key, n_regionkey FROM nation")
def dim_nation(spark, sf_dir):
    return dimension(load(spark, sf_dir, "nation"), "n_name", attrs=["n_regionkey"])


@query("SELECT CAST(row_number() OVER (ORDER BY p_brand) - 1 AS BIGINT) AS idx, p_brand AS key FROM (SELECT DISTINCT p_brand FROM part)")
def dim_brand(spark, sf_dir):
    return dimension(load(spark, sf_dir, "part"), "p_brand")


@query(f"SELECT CAST(w AS BIGINT) AS week, DATE '1995-01-02' + CAST(7 * w AS INTEGER) AS first_day, count(*) AS items FROM (SELECT {S_WEEK} AS w FROM lineitem) GROUP BY w")
def dim_week(spark, sf_dir):
    week = F.floor(F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-02").cast("date")) / 7).cast("int")
    return load(spark, sf_dir, "lineitem").groupBy(week.alias("w")).agg(F.count("*").alias("items")).select(F.col("w").cast("long").alias("week"), F.date_add(F.lit("1995-01-02").cast("date"), F.col("w") * 7).alias("first_day"), "items")


@query(f"SELECT p_type, l_partkey AS p_partkey, amount, place FROM (SELECT p_type, l_partkey, sum(l_quantity) AS amount, CAST(row_number() OVER (PARTITION BY p_type ORDER BY sum(l_quantity) DESC, l_partkey) - 1 AS INTEGER) AS place FROM {SALES} GROUP BY p_type, l_partkey) WHERE place < 50")
def dim_part_top50(spark, sf_dir):
    return top_items(W.sales(spark, sf_dir), "p_type", "p_partkey", "l_quantity", 50)


# --- views -----------------------------------------------------------------------------------------------------------

REGION = "(SELECT n_nationkey AS m, n_regionkey AS g FROM nation)"
NBW, MIXED, SENSOR = CUBE_SQL["retail_nbw"], CUBE_SQL["mixed_ntm"], CUBE_SQL["sensor_utd"]
NBW_SHAPE, MIXED_SHAPE, SENSOR_SHAPE = (25, 25, 357), (25, 150, 83), (50, 5, 30)


def view_sql(source: str, i: str = "i", j: str = "j", k: str = "k", v: str = "sum(v)", extra: str = "") -> str:
    return f"SELECT CAST({i} AS BIGINT) AS i, CAST({j} AS BIGINT) AS j, CAST({k} AS BIGINT) AS k, round({v}, 6) + 0.0 AS v FROM ({source}) {extra} GROUP BY 1, 2, 3"


def nbw_views(spark: SparkSession, sf_dir: str, width: int = 4, items: int | None = None, absent: str = "missing") -> tuple[View, View]:
    cells = W.retail_nbw(spark, sf_dir)
    u, v = W.regions(spark, sf_dir), G.fixed_size(25, items) if items else None
    return make_view(cells, NBW_SHAPE, absent=absent, k=G.period(357, width)), make_view(cells, NBW_SHAPE, absent=absent, i=u, j=v)


@query(view_sql(NBW, k="k // 4"))
def view_t_mod(spark, sf_dir):
    return nbw_views(spark, sf_dir)[0].cells


@query(view_sql(NBW, k="k // 12"))
def view_t_high(spark, sf_dir):
    return nbw_views(spark, sf_dir, 12)[0].cells


@query(view_sql(NBW, i="g", extra=f"JOIN {REGION} ON m = i"))
def view_c_single(spark, sf_dir):
    return nbw_views(spark, sf_dir)[1].cells


@query(view_sql(MIXED, i="g", j="j // 25", extra=f"JOIN {REGION} ON m = i"))
def view_c_double(spark, sf_dir):
    return make_view(W.mixed_ntm(spark, sf_dir), MIXED_SHAPE, i=W.regions(spark, sf_dir), j=G.fixed_size(150, 25)).cells


@query(f"SELECT i, j, w AS k, round(sum(v), 6) + 0.0 AS v FROM (SELECT i, j, CAST(k // 4 AS BIGINT) AS w, v FROM ({NBW})) GROUP BY i, j, w HAVING count(*) = least(4, 357 - 4 * w)")
def view_t_all_atoms(spark, sf_dir):
    return make_view(W.retail_nbw(spark, sf_dir), NBW_SHAPE, "all", k=G.period(357, 4)).cells


@query(view_sql(SENSOR, k="k // 7", v="sum(v / least(7, 30 - 7 * (k // 7)))"))
def view_avg_t(spark, sf_dir):
    return rounded(make_view(W.sensor_utd(spark, sf_dir), SENSOR_SHAPE, k=G.period(30, 7, how="avg")).cells)


@query(view_sql(SENSOR, i="i // 10", v="sum(v / 10)"))
def view_avg_c(spark, sf_dir):
    return rounded(make_view(W.sensor_utd(spark, sf_dir), SENSOR_SHAPE, i=G.fixed_size(50, 10, "avg")).cells)


@query(f"SELECT 4 AS width, i, j, k, v FROM ({view_sql(NBW, k='k // 4')}) UNION ALL SELECT 12, i, j, k, v FROM ({view_sql(NBW, k='k // 12')}) UNION ALL SELECT 52, i, j, k, v FROM ({view_sql(NBW, k='k // 48')})".replace("SELECT 52,", "SELECT 48,"))
def view_all_levels(spark, sf_dir):
    """A ladder of levels, each from the one below: the facts are read for the finest only."""
    fine = nbw_views(spark, sf_dir)[0]
    mid = coarser(fine, k=G.fixed_size(90, 3))
    top = coarser(mid, k=G.fixed_size(30, 4))
    tagged = [v.cells.select(F.lit(w).alias("width"), "i", "j", "k", "v") for w, v in ((4, fine), (12, mid), (48, top))]
    return tagged[0].unionByName(tagged[1]).unionByName(tagged[2])


@query(f"SELECT r_name, n_name, sum(v) AS v, CAST(grouping_id(r_name, n_name) AS BIGINT) AS level FROM ({NBW}) JOIN nation ON n_nationkey = i JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)")
def view_rollup(spark, sf_dir):
    named = W.retail_nbw(spark, sf_dir).join(load(spark, sf_dir, "nation"), F.col("i") == F.col("n_nationkey")).join(load(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return named.rollup("r_name", "n_name").agg(F.sum("v").alias("v"), F.grouping_id().alias("level"))


@query(f"SELECT g, j // 5 AS items, sum(v) AS v FROM ({NBW}) JOIN {REGION} ON m = i GROUP BY GROUPING SETS ((g, j // 5), (g), (j // 5), ())")
def view_grouping_sets(spark, sf_dir):
    W.retail_nbw(spark, sf_dir).join(load(spark, sf_dir, "nation"), F.col("i") == F.col("n_nationkey")).createOrReplaceTempView("finegrain_cells")
    return spark.sql("SELECT n_regionkey AS g, items, sum(v) AS v FROM (SELECT n_regionkey, j DIV 5 AS items, v FROM finegrain_cells) GROUP BY GROUPING SETS ((n_regionkey, items), (n_regionkey), (items), ())")


def calendar_sql(spec: list[tuple[int, int]]) -> str:
    rows = ", ".join(f"({n}, {a}, {b})" for n, (a, b) in enumerate(spec))
    return view_sql(NBW, k="p.n", extra=f"JOIN (VALUES {rows}) p(n, a, b) ON k >= p.a AND k < p.b")


def calendar_view(spark, sf_dir, spec):
    return make_view(W.retail_nbw(spark, sf_dir), NBW_SHAPE, k=G.calendar(357, spec)).cells


for _name, _spec in {"mixed": G.mixed_calendar(357, 4, 12), "gap": G.gapped_calendar(357, 4), "overlap": G.overlapping_calendar(357, 8)}.items():
    query(calendar_sql(_spec), f"calendar_{_name}")(lambda spark, sf_dir, s=_spec: calendar_view(spark, sf_dir, s))


# --- masks -----------------------------------------------------------------------------------------------------------

@query(f"SELECT * FROM ({NBW}) WHERE (7919 * i + 104729 * j + 1299709 * k) % 1000 >= 200")
def mask_random(spark, sf_dir):
    return masks.mask_random(W.retail_nbw(spark, sf_dir), 0.2)


@query(f"SELECT * FROM ({NBW}) WHERE (7919 * i + 104729 * j) % 1000 >= 200")
def mask_fiber(spark, sf_dir):
    return masks.mask_fiber(W.retail_nbw(spark, sf_dir), "k", 0.2)


@query(f"SELECT * FROM ({NBW}) WHERE k % 3 = 1")
def mask_regular(spark, sf_dir):
    return masks.mask_regular(W.retail_nbw(spark, sf_dir), "k", 3, 1)


@query(f"SELECT c.* FROM ({NBW}) c SEMI JOIN (SELECT i AS a, j AS b FROM ({NBW}) GROUP BY 1, 2 HAVING sum(v) > 2000) ON a = i AND b = j")
def mask_structural(spark, sf_dir):
    cells = W.retail_nbw(spark, sf_dir)
    return masks.mask_structural(cells, cells.groupBy("i", "j").agg(F.sum("v").alias("s")).where("s > 2000"), ("i", "j"))


@query(f"SELECT CAST(k AS BIGINT) AS k, coalesce(n, 0) AS observed, coalesce(n, 0) >= 40 AS enough FROM range(0, 357) t(k) LEFT JOIN (SELECT k AS kk, count(*) AS n FROM ({view_sql(NBW, i='g', extra=f'JOIN {REGION} ON m = i')}) GROUP BY k) ON kk = k", name="slab_check")
def _slab_check(spark, sf_dir):
    return slab_check(nbw_views(spark, sf_dir)[1].cells, 357, 40)


# --- estimators in closed form ------------------------------------------------------------------------------------------

ORDERS, DEPT, DOCS = CUBE_SQL["orders_ncm"], CUBE_SQL["dept_stm"], CUBE_SQL["docs_sln"]


def axis(letter: str, least: int) -> str:
    """Indexes of a mode: those of the cells, ``least`` of them at least."""
    return f"(SELECT CAST(unnest(range(0, (SELECT greatest({least}, coalesce(max({letter}), 0) + 1) FROM cells))) AS BIGINT) AS {letter})"


def closed_sql(source: str, shape: str, u: str, v: str, width: int) -> str:
    """CTEs cells and shares(i, j, k, v, t, c, b): the shares of both views and of the blocks of a cube of this size or the cells' own."""
    n_i, n_j, n_k = shape.split(",")
    return f"""cells AS ({source}), dense AS (
  SELECT a.i, b.j, d.k, {u} AS u, {v} AS vv, d.k // {width} AS w, coalesce(x.v, 0) AS v
  FROM {axis("i", n_i)} a, {axis("j", n_j)} b, {axis("k", n_k)} d LEFT JOIN cells x ON x.i = a.i AND x.j = b.j AND x.k = d.k
), shares AS (
  SELECT i, j, k, v, sum(v) OVER (PARTITION BY i, j, w) / count(*) OVER (PARTITION BY i, j, w) AS t, sum(v) OVER (PARTITION BY u, vv, k) / count(*) OVER (PARTITION BY u, vv, k) AS c,
    sum(v) OVER (PARTITION BY u, vv, w) / count(*) OVER (PARTITION BY u, vv, w) AS b FROM dense)"""


ORDERS_X = closed_sql(ORDERS, "25,25,80", "(SELECT n_regionkey FROM nation WHERE n_nationkey = a.i)", "b.j", 3)
DEPT_X = closed_sql(CUBE_SQL["dept_qtm"], "100,6,83", "a.i // 5", "b.j // 3", 4)
NBW_X = closed_sql(NBW, "25,25,357", "(SELECT n_regionkey FROM nation WHERE n_nationkey = a.i)", "b.j", 4)


def orders_views(spark, sf_dir):
    cells, shape = W.orders_ncm(spark, sf_dir), (25, 25, 80)
    return cells, shape, make_view(cells, shape, absent="zero", k=G.period(80, 3)), make_view(cells, shape, absent="zero", i=W.regions(spark, sf_dir))


def dept_views(spark, sf_dir):
    """The whole cube: sizes are those of the tables, in the SQL too."""
    cells = W.dept_qtm(spark, sf_dir)
    shape = W.extent(cells, W.CUBES["dept_qtm"][1])
    return cells, shape, make_view(cells, shape, absent="zero", k=G.period(shape[2], 4)), make_view(cells, shape, absent="zero", i=G.fixed_size(shape[0], 5), j=G.fixed_size(shape[1], 3))


def keys_of(spark, shape):
    return W.grid(spark, shape)


@query(f"WITH {ORDERS_X} SELECT i, j, k, round((t + c) / 2, 4) + 0.0 AS v FROM shares")
def mean_split_A(spark, sf_dir):
    _, shape, t, c = orders_views(spark, sf_dir)
    return rounded(mean_split(keys_of(spark, shape), t, c), 4)


@query(f"WITH {DEPT_X} SELECT i, j, k, round((t + c) / 2, 4) + 0.0 AS v FROM shares")
def mean_split_B(spark, sf_dir):
    _, shape, t, c = dept_views(spark, sf_dir)
    return rounded(mean_split(keys_of(spark, shape), t, c), 4)


@query(f"""
WITH cells AS ({ORDERS}), yt AS (SELECT * FROM (SELECT i, j, k // 3 AS w, sum(v) AS v FROM cells GROUP BY 1, 2, 3) WHERE (7919 * i + 104729 * j + 1299709 * w) % 1000 >= 300),
yc AS (SELECT * FROM (SELECT g, j, k, sum(v) AS v FROM cells JOIN {REGION} ON m = i GROUP BY 1, 2, 3) WHERE (7919 * g + 104729 * j + 1299709 * k) % 1000 >= 300)
SELECT CAST(a.i AS BIGINT) AS i, CAST(b.j AS BIGINT) AS j, CAST(d.k AS BIGINT) AS k,
  round(CASE WHEN yt.v IS NOT NULL AND yc.v IS NOT NULL THEN (yt.v / least(3, 80 - 3 * (d.k // 3)) + yc.v / 5) / 2 ELSE coalesce(yt.v / least(3, 80 - 3 * (d.k // 3)), yc.v / 5) END, 4) + 0.0 AS v
FROM range(0, 25) a(i) JOIN {REGION} ON m = a.i CROSS JOIN range(0, 25) b(j) CROSS JOIN range(0, 80) d(k)
LEFT JOIN yt ON yt.i = a.i AND yt.j = b.j AND yt.w = d.k // 3 LEFT JOIN yc ON yc.g = REGION.g AND yc.j = b.j AND yc.k = d.k""".replace(f"JOIN {REGION} ON m = a.i CROSS", "JOIN (SELECT n_nationkey AS m, n_regionkey AS g FROM nation) AS groups ON m = a.i CROSS").replace("REGION.g", "groups.g"))
def mean_split_masked(spark, sf_dir):
    cells, shape, t, c = orders_views(spark, sf_dir)
    hide = lambda v: View(masks.mask_random(v.cells, 0.3), shape, v.groupings)
    return rounded(mean_split(keys_of(spark, shape), hide(t), hide(c)), 4)


@query(f"WITH {ORDERS_X} SELECT round((t + c) / 2, 4) + 0.0 AS v FROM shares WHERE i = 0 AND j = 0 AND k = 0")
def mean_worked_example(spark, sf_dir):
    """One cell worked out: a nation's orders of a segment and priority over three months, and its region's in the first of them, each split evenly."""
    _, shape, t, c = orders_views(spark, sf_dir)
    return rounded(mean_split(keys_of(spark, shape).where("i = 0 AND j = 0 AND k = 0"), t, c).select("v"), 4)


@query(f"WITH {ORDERS_X} SELECT i, j, k, round(t + c - b, 4) + 0.0 AS v FROM shares")
def min_norm_A(spark, sf_dir):
    _, shape, t, c = orders_views(spark, sf_dir)
    return rounded(min_norm_closed(keys_of(spark, shape), t, c), 4)


@query(f"WITH {DEPT_X} SELECT i, j, k, round(t + c - b, 4) + 0.0 AS v FROM shares")
def min_norm_B(spark, sf_dir):
    _, shape, t, c = dept_views(spark, sf_dir)
    return rounded(min_norm_closed(keys_of(spark, shape), t, c), 4)


@query(f"WITH {DEPT_X} SELECT i, j, k, round(t + c - b, 2) + 0.0 AS v FROM shares WHERE round(t + c - b, 2) <> 0")
def min_norm_blocks(spark, sf_dir):
    """The same solution by conjugate gradients on blocks (of which those without data, all zero, have no rows)."""
    _, _, t, c = dept_views(spark, sf_dir)
    return rounded(ls_blocks(t, c), 2).where("v <> 0")


@query(f"WITH {NBW_X} SELECT round(sum(power(v - (t + c) / 2, 2)) / sum(v * v), 6) AS nde, count(*) AS n_cells FROM shares", name="nde_mean_A")
def _nde_mean(spark, sf_dir):
    t, c = nbw_views(spark, sf_dir, absent="zero")
    truth = densify(W.retail_nbw(spark, sf_dir), dict(zip("ijk", NBW_SHAPE)))
    return rounded(metrics.nde(truth, mean_split(keys_of(spark, NBW_SHAPE), t, c)))


@query(f"WITH {NBW_X} SELECT round(sum(power(v - (t + c - b), 2)) / sum(v * v), 6) AS nde, count(*) AS n_cells FROM shares", name="nde_min_norm_A")
def _nde_min_norm(spark, sf_dir):
    t, c = nbw_views(spark, sf_dir, absent="zero")
    truth = densify(W.retail_nbw(spark, sf_dir), dict(zip("ijk", NBW_SHAPE)))
    return rounded(metrics.nde(truth, min_norm_closed(keys_of(spark, NBW_SHAPE), t, c)))


@query("SELECT 'temporal' AS view, CAST(0 AS DOUBLE) AS relative UNION ALL SELECT 'contemporaneous', 0")
def consistency_min_norm(spark, sf_dir):
    """The minimum-norm estimate has the views it was made from."""
    _, shape, t, c = orders_views(spark, sf_dir)
    x = min_norm_closed(keys_of(spark, shape), t, c)
    gaps = [metrics.consistency(x, v).select(F.lit(n).alias("view"), (F.round("relative", 9) + 0.0).alias("relative")) for n, v in (("temporal", t), ("contemporaneous", c))]
    return gaps[0].unionByName(gaps[1])


@query(f"WITH {DEPT_X} SELECT i, j, k, round(abs(v - (t + c) / 2), 3) AS error FROM shares JOIN cells USING (i, j, k, v) ORDER BY abs(v - (t + c) / 2) DESC, i, j, k LIMIT 20")
def worst_cells(spark, sf_dir):
    cells, shape, t, c = dept_views(spark, sf_dir)
    return metrics.worst_cells(cells, mean_split(keys_of(spark, shape), t, c)).select("i", "j", "k", F.round("error", 3).alias("error"))


# --- one update at rank 2, from factors that SQL can repeat ----------------------------------------------------------------

def factor_sql(name: str, size: int, m: int, p: int, width: int | None = None) -> str:
    """(idx, f0, f1) by the planted integer formula of the first two modes."""
    cols = ", ".join(f"(({m} * x + {p} * {r + 1} + x * x * {r + 2}) % 101) / 100.0 + 0.05 AS {name}{r}" for r in range(2))
    return f"SELECT CAST(x AS BIGINT) AS {name}x, {cols} FROM range(0, {size}) t(x)"


def formula(size: int, m: int, p: int) -> np.ndarray:
    x, r = np.arange(size)[:, None], np.arange(2)[None, :]
    return ((m * x + p * (r + 1) + x * x * (r + 2)) % 101) / 100 + 0.05


def r2_factors() -> dict[str, np.ndarray]:
    return {"i": formula(25, 37, 53), "j": formula(25, 61, 29), "k": formula(357, 17, 71)}


def r2_blind() -> dict[str, np.ndarray]:
    return r2_factors() | {"it": formula(5, 41, 19), "kt": formula(90, 23, 67)}


F2 = f"""a AS ({factor_sql('a', 25, 37, 53)}), b AS ({factor_sql('b', 25, 61, 29)}), c AS ({factor_sql('c', 357, 17, 71)}),
ct AS (SELECT cx // 4 AS ctx, sum(c0) AS ct0, sum(c1) AS ct1 FROM c GROUP BY 1),
au AS (SELECT g AS aux, sum(a0) AS au0, sum(a1) AS au1 FROM a JOIN {REGION} ON m = ax GROUP BY 1),
yt AS ({view_sql(NBW, k='k // 4')}), yc AS ({view_sql(NBW, i='g', extra=f'JOIN {REGION} ON m = i')}),
et AS (SELECT *, a0 * b0 * ct0 + a1 * b1 * ct1 - v AS e FROM yt JOIN a ON ax = i JOIN b ON bx = j JOIN ct ON ctx = k),
ec AS (SELECT *, au0 * b0 * c0 + au1 * b1 * c1 - v AS e FROM yc JOIN au ON aux = i JOIN b ON bx = j JOIN c ON cx = k)"""


def grad_sql(idx: str, t: str, c: str) -> str:
    return f"SELECT CAST({idx} AS BIGINT) AS idx, round(2 * sum(g0), 3) + 0.0 AS g0, round(2 * sum(g1), 3) + 0.0 AS g1 FROM (SELECT {t} UNION ALL SELECT {c}) GROUP BY 1"


R2_GRAD = {
    "a": grad_sql("x", "ax AS x, e * b0 * ct0 AS g0, e * b1 * ct1 AS g1 FROM et", f"m, e * b0 * c0, e * b1 * c1 FROM ec JOIN {REGION} ON g = i"),
    "b": grad_sql("x", "bx AS x, e * a0 * ct0 AS g0, e * a1 * ct1 AS g1 FROM et", "bx, e * au0 * c0, e * au1 * c1 FROM ec"),
    "c": grad_sql("x", "cx AS x, e * a0 * b0 AS g0, e * a1 * b1 AS g1 FROM et JOIN (SELECT cx FROM c) ON cx // 4 = k", "cx, e * au0 * b0, e * au1 * b1 FROM ec"),
}


def gradient_frame(spark, half, name="g"):
    rows = [(i, *(float(x) for x in row)) for i, row in enumerate(2 * half)]
    return rounded(spark.createDataFrame(rows, f"idx long, {name}0 double, {name}1 double"), 3)


@query(f"WITH {F2} SELECT round((SELECT sum(e * e) FROM et) + (SELECT sum(e * e) FROM ec), 3) AS loss")
def coupled_loss_r2(spark, sf_dir):
    return rounded(spark.createDataFrame([(coupled_loss(r2_factors(), list(nbw_views(spark, sf_dir))),)], "loss double"), 3)


for _mode, _letter in zip("ijk", "abc"):
    query(f"WITH {F2} {R2_GRAD[_letter]}", f"grad_{_letter}_r2")(
        lambda spark, sf_dir, m=_mode: gradient_frame(spark, half_gradient([ViewKernel(v) for v in nbw_views(spark, sf_dir)], r2_factors(), m)[0]))


@query(f"""WITH {F2}, ga AS (SELECT x AS gx, 2 * sum(g0) AS g0, 2 * sum(g1) AS g1 FROM (SELECT ax AS x, e * b0 * ct0 AS g0, e * b1 * ct1 AS g1 FROM et UNION ALL SELECT m, e * b0 * c0, e * b1 * c1 FROM ec JOIN {REGION} ON g = i) GROUP BY 1),
gu AS (SELECT g AS gux, sum(g0) AS u0, sum(g1) AS u1 FROM ga JOIN {REGION} ON m = gx GROUP BY 1),
n AS (SELECT sum(g0 * g0 + g1 * g1) / 2 AS top, (SELECT sum(power(g0 * b0 * ct0 + g1 * b1 * ct1, 2)) FROM et JOIN ga ON gx = i) + (SELECT sum(power(u0 * b0 * c0 + u1 * b1 * c1, 2)) FROM ec JOIN gu ON gux = i) AS below FROM ga)
SELECT round(top / below * 1000000, 6) AS step, round((SELECT sum(e * e) FROM et) + (SELECT sum(e * e) FROM ec) - top * top / below, 2) AS loss_after FROM n""")
def step_a_r2(spark, sf_dir):
    kernels, f = [ViewKernel(v) for v in nbw_views(spark, sf_dir)], r2_factors()
    half, loss, _ = half_gradient(kernels, f, "i")
    step, top, below = exact_step(kernels, f, "i", 2 * half)
    return rounded(spark.createDataFrame([(step * 1e6, round(loss - top**2 / below, 2))], "step double, loss_after double"), 6)


@query(f"WITH {F2} SELECT CAST(ax AS BIGINT) AS idx, round(sum(v * b0 * ct0), 5) + 0.0 AS g0, round(sum(v * b1 * ct1), 5) + 0.0 AS g1 FROM et GROUP BY ax")
def mttkrp_r2(spark, sf_dir):
    """The raw sums by the expression kernel: one plan in generated code."""
    f, t = r2_factors(), nbw_views(spark, sf_dir)[0]
    coarse = {m: factor_frame(spark, x) for m, x in t.coarse(f).items()}
    return rounded(expression_pass(t.cells, coarse, "i", 2, "raw"), 5)


@query(f"WITH b AS (SELECT {QUANTITY} AS b0, CAST(count(*) AS DOUBLE) AS b1 FROM {SALES} GROUP BY p_brand) SELECT r, s, x FROM (SELECT 0 AS r, 0 AS s, sum(b0 * b0) AS x FROM b UNION ALL SELECT 0, 1, sum(b0 * b1) FROM b UNION ALL SELECT 1, 0, sum(b0 * b1) FROM b UNION ALL SELECT 1, 1, sum(b1 * b1) FROM b)")
def gram_r2(spark, sf_dir):
    """The Gram matrix of a factor on the driver: brands by quantity and number of lines."""
    rows = W.sales(spark, sf_dir).groupBy("p_brand").agg(F.sum("l_quantity").alias("q"), F.count("*").cast("double").alias("n")).select("q", "n").toArrow()
    g = gram(np.stack([c.to_numpy() for c in rows.columns], 1))
    return spark.createDataFrame([(r, s, float(g[r, s])) for r in range(2) for s in range(2)], "r int, s int, x double")


@query(f"WITH a AS ({factor_sql('a', 25, 37, 53)}), b AS ({factor_sql('b', 25, 61, 29)}), c AS ({factor_sql('c', 357, 17, 71)}) SELECT i, j, k, round(a0 * b0 * c0 + a1 * b1 * c1, 9) AS x FROM ({NBW}) JOIN a ON ax = i JOIN b ON bx = j JOIN c ON cx = k")
def reconstruct_r2(spark, sf_dir):
    return rounded(reconstruct_sql(W.retail_nbw(spark, sf_dir).select("i", "j", "k"), r2_factors(), "x"), 9)


@query(f"WITH a AS ({factor_sql('a', 25, 37, 53)}), b AS ({factor_sql('b', 25, 61, 29)}), c AS ({factor_sql('c', 357, 17, 71)}) SELECT round(a0 * b0 * c0 + a1 * b1 * c1, 9) AS v FROM a, b, c ORDER BY a0 * b0 * c0 + a1 * b1 * c1 DESC LIMIT 25")
def topk_reconstruct(spark, sf_dir):
    return rounded(top_cells(spark, r2_factors(), 25).select("v"), 9)


@query(f"WITH {F2}, x AS (SELECT v, a0 * b0 * c0 + a1 * b1 * c1 AS p FROM ({NBW}) JOIN a ON ax = i JOIN b ON bx = j JOIN c ON cx = k) SELECT round(((SELECT sum(v * v - 2 * v * p) FROM x) + (SELECT sum(power(a0 * b0 * c0 + a1 * b1 * c1, 2)) FROM a, b, c)) / (SELECT sum(v * v) FROM x), 9) AS nde")
def nde_gram_form(spark, sf_dir):
    return rounded(spark.createDataFrame([(metrics.nde_gram(W.retail_nbw(spark, sf_dir), r2_factors()),)], "nde double"), 9)


FB = f"""a AS ({factor_sql('a', 25, 37, 53)}), b AS ({factor_sql('b', 25, 61, 29)}), c AS ({factor_sql('c', 357, 17, 71)}), au AS ({factor_sql('au', 5, 41, 19)}), ct AS ({factor_sql('ct', 90, 23, 67)}),
yt AS ({view_sql(NBW, k='k // 4')}), yc AS ({view_sql(NBW, i='g', extra=f'JOIN {REGION} ON m = i')}),
et AS (SELECT *, a0 * b0 * ct0 + a1 * b1 * ct1 - v AS e FROM yt JOIN a ON ax = i JOIN b ON bx = j JOIN ct ON ctx = k),
ec AS (SELECT *, au0 * b0 * c0 + au1 * b1 * c1 - v AS e FROM yc JOIN au ON aux = i JOIN b ON bx = j JOIN c ON cx = k),
gap AS (SELECT (SELECT sum(c0) FROM c) - (SELECT sum(ct0) FROM ct) AS d0, (SELECT sum(c1) FROM c) - (SELECT sum(ct1) FROM ct) AS d1)"""


def blind_parts(spark, sf_dir):
    t, c = nbw_views(spark, sf_dir)
    plain = lambda v: View(v.cells, v.coarse_shape, {})
    return [ViewKernel(plain(t), {"i": "i", "j": "j", "k": "kt"}), ViewKernel(plain(c), {"i": "it", "j": "j", "k": "k"})], SumPenalty(100.0, np.ones(357))


@query(f"WITH {FB} SELECT round((SELECT sum(e * e) FROM et) + (SELECT sum(e * e) FROM ec) + 100 * (d0 * d0 + d1 * d1), 3) AS loss FROM gap")
def blind_loss_r2(spark, sf_dir):
    kernels, penalty = blind_parts(spark, sf_dir)
    f = r2_blind()
    return rounded(spark.createDataFrame([(sum(k.loss(f) for k in kernels) + penalty.value(f),)], "loss double"), 3)


BLIND_GRAD = {
    "a": ("i", "SELECT ax AS x, sum(e * b0 * ct0) AS g0, sum(e * b1 * ct1) AS g1 FROM et GROUP BY 1"),
    "au": ("it", "SELECT aux AS x, sum(e * b0 * c0) AS g0, sum(e * b1 * c1) AS g1 FROM ec GROUP BY 1"),
    "b": ("j", "SELECT x, sum(g0) AS g0, sum(g1) AS g1 FROM (SELECT bx AS x, e * a0 * ct0 AS g0, e * a1 * ct1 AS g1 FROM et UNION ALL SELECT bx, e * au0 * c0, e * au1 * c1 FROM ec) GROUP BY 1"),
    "c": ("k", "SELECT cx AS x, coalesce(sum(e * au0 * b0), 0) + 100 * any_value(d0) AS g0, coalesce(sum(e * au1 * b1), 0) + 100 * any_value(d1) AS g1 FROM (SELECT cx FROM c) LEFT JOIN (SELECT cx AS ecx, e, au0, au1, b0, b1 FROM ec) ON ecx = cx, gap GROUP BY 1"),
    "ct": ("kt", "SELECT ctx AS x, coalesce(sum(e * a0 * b0), 0) - 100 * any_value(d0) AS g0, coalesce(sum(e * a1 * b1), 0) - 100 * any_value(d1) AS g1 FROM (SELECT ctx FROM ct) LEFT JOIN (SELECT ctx AS etx, e, a0, a1, b0, b1 FROM et) ON etx = ctx, gap GROUP BY 1"),
}


def blind_gradient(spark, sf_dir, name):
    kernels, penalty = blind_parts(spark, sf_dir)
    return gradient_frame(spark, half_gradient(kernels, r2_blind(), name, penalty)[0])


for _letter, (_factor, _body) in BLIND_GRAD.items():
    query(f"WITH {FB} SELECT CAST(x AS BIGINT) AS idx, round(2 * g0, 3) + 0.0 AS g0, round(2 * g1, 3) + 0.0 AS g1 FROM (SELECT {_letter}x AS x, coalesce(g0, 0) AS g0, coalesce(g1, 0) AS g1 FROM {_letter} LEFT JOIN ({_body}) p ON p.x = {_letter}x)", f"blind_grad_{_letter}_r2")(lambda spark, sf_dir, n=_factor: blind_gradient(spark, sf_dir, n))


@query(f"""WITH {FB}, gc AS (SELECT x AS gx, 2 * g0 AS g0, 2 * g1 AS g1 FROM ({BLIND_GRAD['c'][1]})),
n AS (SELECT sum(g0 * g0 + g1 * g1) / 2 AS top, (SELECT sum(power(au0 * b0 * g0 + au1 * b1 * g1, 2)) FROM ec JOIN gc ON gx = k) + 100 * (power(sum(g0), 2) + power(sum(g1), 2)) AS below FROM gc)
SELECT round(top / below * 1000000, 6) AS step FROM n""")
def blind_step_c_r2(spark, sf_dir):
    kernels, penalty = blind_parts(spark, sf_dir)
    half, _, _ = half_gradient(kernels, r2_blind(), "k", penalty)
    return rounded(spark.createDataFrame([(exact_step(kernels, r2_blind(), "k", 2 * half, penalty)[0] * 1e6,)], "step double"))


# --- bounds, costs, score tables ------------------------------------------------------------------------------------------

SIZES = [
    ("retail_nbw A-mod", 25, 25, 5, 25, 90), ("retail_nbw A-high", 25, 25, 3, 25, 30), ("retail_nbw B-5", 25, 25, 5, 5, 90), ("retail_nbw B-3", 25, 25, 5, 3, 30),
    ("mixed B-a", 25, 150, 5, 150, 21), ("mixed B-c", 25, 150, 5, 6, 7), ("incident B-c", 150, 50, 8, 3, 5), ("dept A-mod", 100, 6, 34, 6, 21), ("docs", 20, 4, 4, 4, 4),
]
SIZES_SQL = "(VALUES " + ", ".join(f"('{r[0]}', {', '.join(map(str, r[1:]))})" for r in SIZES) + ") t(name, n_i, n_j, iu, jv, kw)"


@query(f"SELECT name, CAST(n_i AS BIGINT) AS n_i, CAST(n_j AS BIGINT) AS n_j, CAST(iu AS BIGINT) AS iu, CAST(jv AS BIGINT) AS jv, CAST(kw AS BIGINT) AS kw, CAST(least(n_i * n_j, n_i * kw, n_j * kw, 16 * iu * jv) // 16 AS BIGINT) AS bound FROM {SIZES_SQL}")
def rank_bounds(spark, sf_dir):
    return bounds_frame(spark, SIZES)


@query("SELECT * FROM (VALUES ('A-mod', CAST(0.252101 AS DOUBLE), CAST(0.2 AS DOUBLE)), ('A-high', 0.084034, 0.2), ('B-5', 0.252101, 0.04)) t(level, temporal, contemporaneous)")
def measurement_fraction(spark, sf_dir):
    rows = []
    for name, width, items in (("A-mod", 4, None), ("A-high", 12, None), ("B-5", 4, 5)):
        t, c = nbw_views(spark, sf_dir, width, items)
        rows.append((name, metrics.measurement_fraction(t), metrics.measurement_fraction(c)))
    return rounded(spark.createDataFrame(rows, "level string, temporal double, contemporaneous double"))


#: Level, cube, ticks of a period, first-mode groups (none: the regions), items of a second-mode group.
FLOPS = [("retail_nbw A-mod", "retail_nbw", 4, None, 1), ("retail_nbw A-high", "retail_nbw", 12, 3, 1), ("retail_nbw B-5", "retail_nbw", 4, None, 5), ("mixed B-c", "mixed_ntm", 12, None, 25), ("incident B-c", "incident_utd", 6, 8, 20), ("dept A-mod", "dept_qtm", 4, 5, 1)]
FLOPS_SQL = " UNION ALL ".join(
    f"SELECT '{name}' AS name, CAST(10 * (n_i * n_j * ((n_k + {w - 1}) // {w}) + {u or '(SELECT count(DISTINCT n_regionkey) FROM nation)'} * ((n_j + {v - 1}) // {v}) * n_k) AS BIGINT) AS dominant FROM (SELECT max(i) + 1 AS n_i, max(j) + 1 AS n_j, max(k) + 1 AS n_k FROM ({CUBE_SQL[source]}))"
    for name, source, w, u, v in FLOPS)


@query(FLOPS_SQL)
def flop_model(spark, sf_dir):
    """The dominant operations of a gradient at rank 10, from the sizes that the given cubes have."""
    areas = load(spark, sf_dir, "nation").select("n_regionkey").distinct().count()
    shapes = {source: W.extent(cells_of(spark, sf_dir, source)) for source in {f[1] for f in FLOPS}}
    rows = [(name, costs.dominant(shapes[source], -(-shapes[source][2] // w), u or areas, -(-shapes[source][1] // v), 10)) for name, source, w, u, v in FLOPS]
    return spark.createDataFrame(rows, "name string, dominant long")


PUBLISHED = [
    ("BAT", "mean_split", 0, 0.3284), ("BAT", "min_norm_ls", 0, 0.3328), ("BAT", "coupled_matrix", 0, 0.4254), ("BAT", "coupled_cp", 10, 0.5203), ("BAT", "coupled_cp", 25, 0.5079), ("BAT", "coupled_cp", 40, 0.4972), ("BAT", "cp_oracle", 40, 0.4109), ("BAT", "blind_cp", 40, 0.4914),
    ("BJC", "mean_split", 0, 0.4441), ("BJC", "min_norm_ls", 0, 0.6077), ("BJC", "coupled_matrix", 0, 0.1818), ("BJC", "coupled_cp", 10, 0.1978), ("BJC", "coupled_cp", 25, 0.1684), ("BJC", "coupled_cp", 40, 0.1572), ("BJC", "cp_oracle", 40, 0.0443), ("BJC", "blind_cp", 40, 0.3909),
    ("FSF", "mean_split", 0, 0.5609), ("FSF", "min_norm_ls", 0, 0.5982), ("FSF", "coupled_matrix", 0, 0.1930), ("FSF", "coupled_cp", 10, 0.2019), ("FSF", "coupled_cp", 25, 0.1790), ("FSF", "coupled_cp", 40, 0.1747), ("FSF", "cp_oracle", 40, 0.0399), ("FSF", "blind_cp", 40, 0.1846),
]
SCORES_SQL = "(SELECT w AS workload, 'A-mod' AS level, m AS method, CAST(r AS INT) AS rank, CAST(e AS DOUBLE) AS nde FROM (VALUES " + ", ".join(f"('{w}', '{m}', {r}, {e})" for w, m, r, e in PUBLISHED) + ") t(w, m, r, e))"


def published(spark):
    return spark.createDataFrame([(w, "A-mod", m, r, e) for w, m, r, e in PUBLISHED], "workload string, level string, method string, rank int, nde double")


CATEGORY_X = closed_sql(CUBE_SQL["mixed_ntm"], "25,150,83", "(SELECT n_regionkey FROM nation WHERE n_nationkey = a.i)", "b.j", 4)
PRODUCT_SQL = """CASE WHEN sum(v) OVER (PARTITION BY {u}) > 0 THEN sum(v) OVER (PARTITION BY {u}, i) * (sum(v) OVER (PARTITION BY {u}, j) / sum(v) OVER (PARTITION BY {u})) * (sum(v) OVER (PARTITION BY {u}, k) / sum(v) OVER (PARTITION BY {u})) ELSE 0 END"""
#: Scores of the six categories' cubes: both closed forms, and the products of marginal sums (rank 1) or of each area's (rank 5) as they are and at the best scale.
CATEGORY_SCORES = f"""(WITH {CATEGORY_X}, placed AS (SELECT s.*, j // 25 AS cat, n_regionkey AS area FROM shares s JOIN nation ON n_nationkey = i),
estimates AS (SELECT cat, v, (t + c) / 2 AS mean, t + c - b AS norm, {PRODUCT_SQL.format(u="cat")} AS one, {PRODUCT_SQL.format(u="cat, area")} AS five FROM placed),
errors AS (SELECT cat, sum(power(v - mean, 2)) / sum(v * v) AS mean, sum(power(v - norm, 2)) / sum(v * v) AS norm, sum(power(v - one, 2)) / sum(v * v) AS one, sum(power(v - five, 2)) / sum(v * v) AS five,
  1 - power(sum(v * one), 2) / (sum(v * v) * sum(one * one)) AS one_best, 1 - power(sum(v * five), 2) / (sum(v * v) * sum(five * five)) AS five_best FROM estimates GROUP BY 1)
SELECT list_extract({W.TYPES}, CAST(cat AS INT) + 1) AS workload, 'A-mod' AS level, m AS method, CAST(r AS INT) AS rank, round(CASE n WHEN 0 THEN mean WHEN 1 THEN norm WHEN 2 THEN one WHEN 3 THEN five WHEN 4 THEN one_best ELSE five_best END, 9) AS nde
FROM errors, (VALUES (0, 'mean_split', 0), (1, 'min_norm_ls', 0), (2, 'product_cp', 1), (3, 'product_cp', 5), (4, 'product_oracle', 1), (5, 'product_oracle', 5)) t(n, m, r))"""


def product_of_marginals(cells: DataFrame, *groups: str) -> DataFrame:
    """cells with ``v`` and m: the product of the marginal sums within groups, which are columns, in their scale."""
    total = cells.groupBy(*groups).agg(F.sum("v").alias("_n"))
    out = cells.join(total, [*groups])
    for m in "ijk":
        out = out.join(cells.groupBy(*groups, m).agg(F.sum("v").alias(f"_{m}")), [*groups, m])
    return out.select("i", "j", "k", F.when(F.col("_n") > 0, F.col("_i") * (F.col("_j") / F.col("_n")) * (F.col("_k") / F.col("_n"))).otherwise(0.0).alias("m"))


def category_scores(spark, sf_dir) -> DataFrame:
    """workload, level, method, rank, nde of the categories' cubes by nation, brand and month."""
    cells = W.mixed_ntm(spark, sf_dir)
    shape = W.extent(cells, W.CUBES["mixed_ntm"][1])
    t, c = make_view(cells, shape, absent="zero", k=G.period(shape[2], 4)), make_view(cells, shape, absent="zero", i=W.regions(spark, sf_dir))
    areas = load(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("i"), F.col("n_regionkey").alias("area"))
    truth = W.shared.table(densify(cells, dict(zip("ijk", shape))).withColumn("cat", F.floor(F.col("j") / 25)).join(F.broadcast(areas), "i"))
    keys = keys_of(spark, shape)
    renamed = lambda df, name: df.withColumnRenamed("v" if "v" in df.columns else "m", name)
    estimates = {"mean": mean_split(keys, t, c), "norm": min_norm_closed(keys, t, c), "one": product_of_marginals(truth, "cat"), "five": product_of_marginals(truth, "cat", "area")}
    both = reduce(lambda a, b: a.join(b, ["i", "j", "k"]), [renamed(df, name) for name, df in estimates.items()], truth)
    squares = F.sum(F.col("v") ** 2)
    error = lambda n: F.sum((F.col("v") - F.col(n)) ** 2) / squares
    best = lambda n: 1 - F.sum(F.col("v") * F.col(n)) ** 2 / (squares * F.sum(F.col(n) ** 2))
    scored = [("mean_split", 0, error("mean")), ("min_norm_ls", 0, error("norm")), ("product_cp", 1, error("one")), ("product_cp", 5, error("five")), ("product_oracle", 1, best("one")), ("product_oracle", 5, best("five"))]
    rows = both.groupBy("cat").agg(F.array(*(F.struct(F.lit(m).alias("method"), F.lit(r).alias("rank"), F.round(e, 9).alias("nde")) for m, r, e in scored)).alias("s"))
    name = F.element_at(F.array(*map(F.lit, W.TYPES)), F.col("cat").cast("int") + 1)
    return rows.select(name.alias("workload"), F.lit("A-mod").alias("level"), F.explode("s").alias("s")).select("workload", "level", "s.method", "s.rank", "s.nde")


@query(f"SELECT workload, level, method, nde, rank, CAST(place AS INT) AS place, CASE place WHEN 1 THEN 'best' WHEN 2 THEN 'second' END AS mark FROM (SELECT workload, level, method, min(nde) AS nde, arg_min(rank, nde) AS rank, dense_rank() OVER (PARTITION BY workload, level ORDER BY min(nde)) AS place FROM {CATEGORY_SCORES} GROUP BY 1, 2, 3)", name="leaderboard")
def _leaderboard(spark, sf_dir):
    return metrics.leaderboard(category_scores(spark, sf_dir))


@query(f"SELECT workload, level, baseline, ours, round(baseline / ours, 9) AS ratio, round(1 - ours / baseline, 9) AS reduction FROM (SELECT workload, level, min(nde) FILTER (WHERE method NOT IN ('product_cp', 'product_oracle')) AS baseline, min(nde) FILTER (WHERE method = 'product_cp') AS ours FROM {CATEGORY_SCORES} GROUP BY 1, 2)", name="improvement")
def _improvement(spark, sf_dir):
    return rounded(metrics.improvement(category_scores(spark, sf_dir), ("product_cp",), "product_oracle"), 9, "ratio", "reduction")


@query(f"SELECT a.workload, a.level, a.rank, a.nde, b.nde AS floor, round(a.nde - b.nde, 9) AS gap FROM {CATEGORY_SCORES} a JOIN {CATEGORY_SCORES} b USING (workload, level, rank) WHERE a.method = 'product_cp' AND b.method = 'product_oracle'", name="oracle_gap")
def _oracle_gap(spark, sf_dir):
    return rounded(metrics.oracle_gap(category_scores(spark, sf_dir), "product_cp", "product_oracle"), 9, "gap")


@query(f"SELECT *, nde <= 1.1 * min(nde) OVER (PARTITION BY workload, level, method) AS usable FROM {SCORES_SQL}", name="rank_plateau")
def _rank_plateau(spark, sf_dir):
    return metrics.rank_plateau(published(spark))


# --- cosine basis, planted cubes ---------------------------------------------------------------------------------------------

BASIS_SQL = "SELECT CAST(m AS BIGINT) AS m, CAST(k AS BIGINT) AS k, CASE WHEN m = 0 THEN sqrt(1 / 30.0) ELSE sqrt(2 / 30.0) END * cos(pi() * m * (2 * k + 1) / 60.0) AS value FROM range(0, 30) a(m), range(0, 30) b(k)"


@query(f"""SELECT m, k, round(CASE WHEN m = 0 THEN sqrt(1.0 / n) ELSE sqrt(2.0 / n) END * cos(pi() * m * (2 * k + 1) / (2.0 * n)), 9) + 0.0 AS value
FROM (SELECT n, m, unnest(range(0, n)) AS k FROM (SELECT n, unnest(range(0, n)) AS m FROM (SELECT max({S_DAY}) + 1 AS n FROM events)))""")
def dct_basis(spark, sf_dir):
    """The basis for as many days as the events have."""
    functions.register(spark)
    W.sensor_utd(spark, sf_dir).agg((F.max("k") + 1).cast("int").alias("n")).createOrReplaceTempView("finegrain_days")
    return rounded(spark.sql("SELECT b.m, b.k, b.value FROM finegrain_days d, LATERAL dct_basis(d.n) b"), 9)


@query(f"SELECT i, j, CAST(b.m AS BIGINT) AS m, round(sum(v * value), 6) + 0.0 AS s FROM ({SENSOR}) x JOIN ({BASIS_SQL}) b ON b.k = x.k GROUP BY 1, 2, 3")
def dct_transform(spark, sf_dir):
    functions.register(spark)
    basis = spark.sql("SELECT * FROM dct_basis(30)")
    return rounded(W.sensor_utd(spark, sf_dir).join(F.broadcast(basis), "k").groupBy("i", "j", "m").agg(F.sum(F.col("v") * F.col("value")).alias("s")))


def planted_sql(rank: int, ticks: int = 60) -> str:
    terms = " + ".join(
        f"(((37 * i + {53 * (r + 1)} + i * i * {r + 2}) % 101) / 100.0 + 0.05) * (((61 * j + {29 * (r + 1)} + j * j * {r + 2}) % 101) / 100.0 + 0.05) * (1 + 0.9 * sin(2 * pi() * (k * {r + 1} / 52.0 + ((13 * k) % 7) / 7.0 * {r % 2} + {0.17 * r})))"
        for r in range(rank))
    return f"SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, CAST(k AS BIGINT) AS k, 100 * ({terms}) AS v FROM range(0, 25) a(i), range(0, 25) b(j), range(0, {ticks}) c(k)"


# Low rank by construction from a given table: within each of the six types, quantities as if nation, brand and week were independent.
MARGINAL_SQL = f"""WITH s AS (SELECT s_nationkey AS i, {S_BRAND} AS j, {S_WEEK} AS k, {S_TYPE} AS r, l_quantity AS q FROM {SALES}),
a AS (SELECT i, r, sum(q) AS x FROM s GROUP BY 1, 2), b AS (SELECT j, r, sum(q) AS x FROM s GROUP BY 1, 2), c AS (SELECT k, r, sum(q) AS x FROM s GROUP BY 1, 2), n AS (SELECT r, sum(q) AS x FROM s GROUP BY 1)
SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, CAST(k AS BIGINT) AS k, round(sum(a.x * b.x * (c.x / (n.x * n.x))), 6) + 0.0 AS v FROM a JOIN b USING (r) JOIN c USING (r) JOIN n USING (r) GROUP BY 1, 2, 3"""


def marginals(spark, sf_dir) -> list[DataFrame]:
    """For each mode (i, j, k): its index, the type r and the quantity x; of weeks, divided by the type's squared quantity."""
    by = W.retail_by_type(spark, sf_dir)
    a, b, c = (by.groupBy(m, "r").agg(F.sum("v").alias("x")) for m in "ijk")
    n = by.groupBy("r").agg(F.sum("v").alias("n"))
    return [a, b, c.join(n, "r").select("k", "r", (F.col("x") / (F.col("n") * F.col("n"))).alias("x"))]


@query(MARGINAL_SQL)
def cube_planted_expression(spark, sf_dir):
    """The cube of rank six that has the given quantities by type and nation, brand or week: joins and products, no Python."""
    a, b, c = (x.withColumnRenamed("x", f"x{n}") for n, x in enumerate(marginals(spark, sf_dir)))
    terms = a.join(b, "r").join(c, "r").withColumn("x", F.col("x0") * F.col("x1") * F.col("x2"))
    return rounded(terms.groupBy("i", "j", "k").agg(F.sum("x").alias("v")))


@query(MARGINAL_SQL)
def cube_planted(spark, sf_dir):
    """The same cube by the data source: the factors are the given quantities by type; a cell that no type reaches is none."""
    spark.dataSource.register(PlantedCubeSource)
    factors = []
    for m, frame in zip("ijk", marginals(spark, sf_dir)):
        index, r, x = (column.to_numpy() for column in frame.select(m, "r", "x").toArrow().columns)
        factors.append(np.zeros((int(index.max(initial=-1)) + 1, len(W.TYPES))))
        factors[-1][index, r] = x
    cells = spark.read.format("planted_cube").option("size", ",".join(str(len(f)) for f in factors)).option("factors", json.dumps([f.tolist() for f in factors])).load()
    return rounded(cells.where("v > 0"))


def planted_views(spark, sf_dir, width: int = 4, rank: int = 4):
    w = W.workload(spark, sf_dir, f"planted{rank}")
    level = next(x for x in w.levels if x.name == ("A-mod" if width == 4 else "A-high"))
    t, c = (v.placed() for v in w.views(level))
    return w, t, c


def verdict(spark, method, flags: dict[str, bool], errors: dict[str, float]):
    """One row: flags, and errors as they are compared (rounded)."""
    names, values = sorted(flags), sorted(errors)
    row = (method, *(bool(flags[n]) for n in names), *(float(errors[n]) for n in values))
    return spark.createDataFrame([row], "method string, " + ", ".join([*(f"{n} boolean" for n in names), *(f"{n} double" for n in values)]))


PLANTED_X = closed_sql(planted_sql(4, 357), "25,25,357", "(SELECT n_regionkey FROM nation WHERE n_nationkey = a.i)", "b.j", 4)
NDE_SQL = {"mean": "round(sum(power(v - (t + c) / 2, 2)) / sum(v * v), 4)", "min_norm": "round(sum(power(v - (t + c - b), 2)) / sum(v * v), 4)"}


def verdict_sql(method: str, flags: dict[str, bool], own: float, source: str = PLANTED_X, mean: str = NDE_SQL["mean"]) -> str:
    """What a fit must show. The even split's error is computed here; a fit's own error is stated to two digits."""
    said = ", ".join(f"{str(x).upper()} AS {n}" for n, x in sorted(flags.items()))
    return f"WITH {source} SELECT '{method}' AS method, {said}, {mean} AS mean_nde, CAST({own} AS DOUBLE) AS own_nde FROM shares"


def planted_mean(w, t, c) -> float:
    return metrics.nde_value(w.cells, mean_split(keys_of(w.cells.sparkSession, w.shape), t, c))


@query(verdict_sql("coupled_cp", {"monotone": True, "beats_mean": True, "beats_min_norm": True}, 0.0))
def coupled_planted(spark, sf_dir):
    w, t, c = planted_views(spark, sf_dir)
    fit = fit_coupled([t, c], 10, placed=True)
    own, mean = metrics.nde_model(w.cells, fit.factors), planted_mean(w, t, c)
    norm = metrics.nde_value(w.cells, min_norm_closed(keys_of(spark, w.shape), t, c))
    return verdict(spark, "coupled_cp", {"monotone": fit.monotone, "beats_mean": own < mean, "beats_min_norm": own < norm}, {"mean_nde": round(mean, 4), "own_nde": round(own, 2)})


@query(verdict_sql("two_stage", {"recovers": True, "beats_mean": True}, 0.0))
def two_stage_planted(spark, sf_dir):
    w, t, c = planted_views(spark, sf_dir)
    own, mean = metrics.nde_model(w.cells, fit_two_stage(t, c, 4, 150).factors), planted_mean(w, t, c)
    return verdict(spark, "two_stage", {"recovers": own < 1e-4, "beats_mean": own < mean}, {"mean_nde": round(mean, 4), "own_nde": round(own, 2)})


@query(verdict_sql("cp_oracle", {"below_coupled": True, "beats_mean": True}, 0.0))
def cp_oracle_planted(spark, sf_dir):
    """The decomposition of the true cube bounds what the coupled method can reach at the same rank."""
    w, t, c = planted_views(spark, sf_dir)
    own, mean = metrics.nde_model(w.cells, fit_cp(w.cells, w.shape, 10, 20).factors), planted_mean(w, t, c)
    coupled = metrics.nde_model(w.cells, fit_coupled([t, c], 10, placed=True).factors)
    return verdict(spark, "cp_oracle", {"below_coupled": own <= coupled, "beats_mean": own < mean}, {"mean_nde": round(mean, 4), "own_nde": round(own, 2)})


@query(verdict_sql("coupled_matrix", {"exact_without_noise": True, "beats_mean": True}, 0.0))
def coupled_matrix_planted(spark, sf_dir):
    w, t, c = planted_views(spark, sf_dir)
    own, mean = metrics.nde_value(w.cells, fit_coupled_matrix(t, c, 4, 3).cells()), planted_mean(w, t, c)
    return verdict(spark, "coupled_matrix", {"exact_without_noise": own < 1e-6, "beats_mean": own < mean}, {"mean_nde": round(mean, 4), "own_nde": round(own, 2)})


@query(verdict_sql("blind_cp", {"monotone": True, "beats_mean": True}, 0.0))
def blind_planted(spark, sf_dir):
    w, t, c = planted_views(spark, sf_dir)
    fit = fit_blind(t, c, 10)
    own, mean = metrics.nde_model(w.cells, fit.factors), planted_mean(w, t, c)
    return verdict(spark, "blind_cp", {"monotone": fit.monotone, "beats_mean": own < mean}, {"mean_nde": round(mean, 4), "own_nde": round(own, 2)})


MASKED_MEAN = """(SELECT round(sum(power(x.v - CASE WHEN yt.v IS NOT NULL AND yc.v IS NOT NULL THEN (yt.v / least(4, 357 - 4 * (x.k // 4)) + yc.v / 5) / 2 ELSE coalesce(yt.v / least(4, 357 - 4 * (x.k // 4)), yc.v / 5, 0) END, 2)) / sum(x.v * x.v), 4)
FROM cells x JOIN nation ON n_nationkey = x.i
LEFT JOIN (SELECT * FROM (SELECT i, j, k // 4 AS w, sum(v) AS v FROM cells GROUP BY 1, 2, 3) WHERE (7919 * i + 104729 * j + 1299709 * w) % 1000 >= 100) yt ON yt.i = x.i AND yt.j = x.j AND yt.w = x.k // 4
LEFT JOIN (SELECT * FROM (SELECT n_regionkey AS g, j, k, sum(v) AS v FROM cells JOIN nation ON n_nationkey = i GROUP BY 1, 2, 3) WHERE (7919 * g + 104729 * j + 1299709 * k) % 1000 >= 100) yc ON yc.g = n_regionkey AND yc.j = x.j AND yc.k = x.k)"""


@query(f"WITH cells AS ({planted_sql(4, 357)}) SELECT 'coupled_cp' AS method, TRUE AS monotone, TRUE AS beats_mean, {MASKED_MEAN} AS mean_nde, CAST(0 AS DOUBLE) AS own_nde")
def coupled_masked_planted(spark, sf_dir):
    """A tenth of both views missing. The start is that of the larger bound: from the published rule's, 10 iterations end above the even split (README)."""
    from finegrain.operators.views import masked

    w, t, c = planted_views(spark, sf_dir)
    t, c = (masked(v, masks.mask_random(v.cells, 0.1)).placed() for v in (t, c))
    fit = fit_coupled([t, c], 4, init="bound", placed=True)
    own, mean = metrics.nde_model(w.cells, fit.factors), planted_mean(w, t, c)
    return verdict(spark, "coupled_cp", {"monotone": fit.monotone, "beats_mean": own < mean}, {"mean_nde": round(mean, 4), "own_nde": round(own, 2)})


def retail_verdict(spark, sf_dir, method: str, fit_views) -> DataFrame:
    """A fit of the given retail cube, which has no low rank: descent is monotone, and the even split is the better estimate."""
    t, c = (v.placed() for v in nbw_views(spark, sf_dir, absent="zero"))
    truth = densify(W.retail_nbw(spark, sf_dir), dict(zip("ijk", NBW_SHAPE)))
    fit = fit_views(t, c)
    own, mean = metrics.nde_model(truth, fit.factors), metrics.nde_value(truth, mean_split(keys_of(spark, NBW_SHAPE), t, c))
    return verdict(spark, method, {"monotone": fit.monotone, "beats_mean": own < mean, "below_zero_estimate": own < 1}, {"mean_nde": round(mean, 4), "own_nde": round(own, 2)})


@query(verdict_sql("coupled_cp", {"monotone": True, "beats_mean": False, "below_zero_estimate": True}, 0.77, NBW_X))
def coupled_retail(spark, sf_dir):
    return retail_verdict(spark, sf_dir, "coupled_cp", lambda t, c: fit_coupled([t, c], 10, placed=True))


@query(verdict_sql("blind_cp", {"monotone": True, "beats_mean": False, "below_zero_estimate": True}, 0.77, NBW_X))
def blind_retail(spark, sf_dir):
    return retail_verdict(spark, sf_dir, "blind_cp", lambda t, c: fit_blind(t, c, 10))


# --- a whole cycle of updates at rank 2 ------------------------------------------------------------------------------------------

def cycle_sql() -> str:
    """Exact steps of the three blocks in turn, each from the factors that the last one left, as one chain of CTEs."""
    parts = [f"a AS ({factor_sql('a', 25, 37, 53)}), b AS ({factor_sql('b', 25, 61, 29)}), c AS ({factor_sql('c', 357, 17, 71)})", f"yt AS ({view_sql(NBW, k='k // 4')}), yc AS ({view_sql(NBW, i='g', extra=f'JOIN {REGION} ON m = i')})"]
    now = {"a": "a", "b": "b", "c": "c"}
    product = lambda names, r: " * ".join(f"{n}{r}" for n in names)
    for x in "abc":
        a, b, c = now["a"], now["b"], now["c"]
        parts.append(f"""ct_{x} AS (SELECT cx // 4 AS ctx, sum(c0) AS ct0, sum(c1) AS ct1 FROM {c} GROUP BY 1), au_{x} AS (SELECT g AS aux, sum(a0) AS au0, sum(a1) AS au1 FROM {a} JOIN {REGION} ON m = ax GROUP BY 1),
et_{x} AS (SELECT *, a0 * b0 * ct0 + a1 * b1 * ct1 - v AS e FROM yt JOIN {a} ON ax = i JOIN {b} ON bx = j JOIN ct_{x} ON ctx = k),
ec_{x} AS (SELECT *, au0 * b0 * c0 + au1 * b1 * c1 - v AS e FROM yc JOIN au_{x} ON aux = i JOIN {b} ON bx = j JOIN {c} ON cx = k)""")
        t_others, c_others = {"a": ("b", "ct"), "b": ("a", "ct"), "c": ("a", "b")}[x], {"a": ("b", "c"), "b": ("au", "c"), "c": ("au", "b")}[x]
        t_rows = c_rows = {"a": "i", "b": "j", "c": "k"}[x]
        et_source = f"et_{x} JOIN (SELECT cx AS tick FROM c) ON tick // 4 = k" if x == "c" else f"et_{x}"
        ec_source = f"ec_{x} JOIN {REGION} ON g = i" if x == "a" else f"ec_{x}"
        t_key, c_key = ("tick" if x == "c" else t_rows), ("m" if x == "a" else c_rows)
        parts.append(f"""g_{x} AS (SELECT x, 2 * sum(p0) AS g0, 2 * sum(p1) AS g1 FROM (SELECT {t_key} AS x, e * {product(t_others, 0)} AS p0, e * {product(t_others, 1)} AS p1 FROM {et_source}
  UNION ALL SELECT {c_key}, e * {product(c_others, 0)}, e * {product(c_others, 1)} FROM {ec_source}) GROUP BY 1)""")
        dt = f"(SELECT x // 4 AS dx, sum(g0) AS d0, sum(g1) AS d1 FROM g_{x} GROUP BY 1)" if x == "c" else f"(SELECT x AS dx, g0 AS d0, g1 AS d1 FROM g_{x})"
        dc = f"(SELECT g AS dx, sum(g0) AS d0, sum(g1) AS d1 FROM g_{x} JOIN {REGION} ON m = x GROUP BY 1)" if x == "a" else f"(SELECT x AS dx, g0 AS d0, g1 AS d1 FROM g_{x})"
        model = lambda names: f"power(d0 * {product(names, 0)} + d1 * {product(names, 1)}, 2)"
        parts.append(f"""s_{x} AS (SELECT (SELECT sum(g0 * g0 + g1 * g1) / 2 FROM g_{x}) / ((SELECT sum({model(t_others)}) FROM et_{x} JOIN {dt} ON dx = {t_rows}) + (SELECT sum({model(c_others)}) FROM ec_{x} JOIN {dc} ON dx = {c_rows})) AS step),
{x}_new AS (SELECT {x}x, {x}0 - step * coalesce(g0, 0) AS {x}0, {x}1 - step * coalesce(g1, 0) AS {x}1 FROM {now[x]} LEFT JOIN g_{x} ON x = {x}x, s_{x})""")
        now[x] = f"{x}_new"
    rows = " UNION ALL ".join(f"SELECT '{m}' AS mode, CAST({x}x AS BIGINT) AS idx, round({x}0, 5) + 0.0 AS f0, round({x}1, 5) + 0.0 AS f1 FROM {x}_new" for m, x in zip("ijk", "abc"))
    return "WITH " + ",\n".join(parts) + " " + rows


@query(cycle_sql())
def one_cycle_r2(spark, sf_dir):
    factors, _ = descend([ViewKernel(v) for v in nbw_views(spark, sf_dir)], r2_factors(), ("i", "j", "k"), 1, rebalance=False)
    rows = [(m, n, float(x), float(y)) for m, f in factors.items() for n, (x, y) in enumerate(f)]
    return rounded(spark.createDataFrame(rows, "mode string, idx long, f0 double, f1 double"), 5)


# --- experiments on the given cubes (scores; no SQL can say them) -----------------------------------------------------------------

@query()
def workload_retail(spark, sf_dir):
    return W.run_whole(spark, sf_dir, "retail_nbw")


@query()
def workload_docs(spark, sf_dir):
    """The one given cube with low rank: all methods at ranks 1 and 2."""
    return W.run(spark, sf_dir, ("docs_sln",), W.METHODS, (1, 2))


@query()
def workload_blind_docs(spark, sf_dir):
    return W.run(spark, sf_dir, ("docs_sln",), ("blind_cp",), (1, 2), offset=1)


@query()
def workload_sensor(spark, sf_dir):
    return W.run_whole(spark, sf_dir, "sensor_utd")


@query()
def workload_departments(spark, sf_dir):
    return W.run_whole(spark, sf_dir, "dept_stm")


@query()
def workload_embeddings(spark, sf_dir):
    return W.run_whole(spark, sf_dir, "embed_lsd")


@query()
def workload_mixed(spark, sf_dir):
    return W.run_whole(spark, sf_dir, "mixed_ntm")


@query()
def workload_incident(spark, sf_dir):
    return W.run_whole(spark, sf_dir, "incident_utd")


@query()
def workload_categories(spark, sf_dir):
    """One cube of the 50 best-selling parts for each category."""
    return W.run_whole(spark, sf_dir, *(f"category_top50/{t}" for t in W.TYPES))


@query()
def workload_scale(spark, sf_dir):
    return W.run_whole(spark, sf_dir, "retail_sbm")


@query()
def workload_missing(spark, sf_dir):
    return W.missing_grid(spark, sf_dir)


@query()
def workload_calendars(spark, sf_dir):
    return W.calendars(spark, sf_dir)


@query()
def workload_ablations(spark, sf_dir):
    return W.ablations(spark, sf_dir, iterations=10)


@query()
def workload_observed(spark, sf_dir):
    return W.run_observed(spark, sf_dir)


@query()
def workload_recovery(spark, sf_dir):
    return W.recovery(spark, sf_dir)


def closed_level(name: str, level: str, source: str, shape: str, u: str, v: str, width: int, periods: int, iu: int, jv: int) -> tuple[str, str]:
    """SQL of what is known of a level without a fit: cells, measured shares, and the errors of both closed forms."""
    key = f"{name}_{level}".replace("-", "_")
    n = "(SELECT count(*) FROM shares)"
    return key, f"""{key} AS (WITH {closed_sql(source, shape, u, v, width)} SELECT '{name}' AS workload, '{level}' AS level, count(*) AS n_cells,
  round({periods} * (SELECT count(*) FROM (SELECT DISTINCT i, j FROM shares)) / {n}, 6) AS temporal, round({iu} * {jv} * (SELECT count(DISTINCT k) FROM shares) / {n}, 6) AS contemporaneous,
  {NDE_SQL["mean"]} AS mean_split, {NDE_SQL["min_norm"]} AS min_norm_ls FROM shares)"""


AREA = "(SELECT n_regionkey FROM nation WHERE n_nationkey = a.i)"
CLOSED_LEVELS = [
    ("retail_nbw", "A-mod", NBW, "25,25,357", AREA, "b.j", 4, 90, 5, 25), ("retail_nbw", "A-high", NBW, "25,25,357", "a.i * 3 // 25", "b.j", 12, 30, 3, 25),
    ("orders_ncm", "A-mod", ORDERS, "25,25,80", AREA, "b.j", 3, 27, 5, 25),
    ("mixed_ntm", "B-a", MIXED, "25,150,83", AREA, "b.j", 4, 21, 5, 150), ("mixed_ntm", "B-b", MIXED, "25,150,83", AREA, "b.j // 10", 4, 21, 5, 15), ("mixed_ntm", "B-c", MIXED, "25,150,83", AREA, "b.j // 25", 12, 7, 5, 6),
    ("incident_utd", "B-a", CUBE_SQL["incident_utd"], "150,50,30", "a.i * 30 // 150", "b.j // 5", 3, 10, 30, 10), ("incident_utd", "B-b", CUBE_SQL["incident_utd"], "150,50,30", "a.i * 15 // 150", "b.j // 10", 3, 10, 15, 5),
    ("incident_utd", "B-c", CUBE_SQL["incident_utd"], "150,50,30", "a.i * 8 // 150", "b.j // 20", 6, 5, 8, 3),
]
CLOSED_PARTS = [closed_level(*x) for x in CLOSED_LEVELS]


@query("WITH " + ", ".join(sql for _, sql in CLOSED_PARTS) + " " + " UNION ALL ".join(f"SELECT * FROM {key}" for key, _ in CLOSED_PARTS))
def workload_closed(spark, sf_dir):
    """What the experiments' levels measure, and the errors of the even split and the minimum norm: the part that needs no fit, checked by SQL."""
    out, cubes = [], {}
    for name, level, *_ in CLOSED_LEVELS:
        w = cubes.get(name) or cubes.setdefault(name, W.workload(spark, sf_dir, name))
        t, c = w.views(next(x for x in w.levels if x.name == level))
        truth = densify(w.cells, dict(zip("ijk", w.shape)))
        both = (metrics.nde(truth, f(keys_of(spark, w.shape), t, c)).select("n_cells", F.col("nde").alias(n)) for f, n in ((mean_split, "mean_split"), (min_norm_closed, "min_norm_ls")))
        row = next(both).join(next(both), "n_cells")
        out.append(row.select(F.lit(name).alias("workload"), F.lit(level).alias("level"), "n_cells", F.lit(round(metrics.measurement_fraction(t), 6)).alias("temporal"), F.lit(round(metrics.measurement_fraction(c), 6)).alias("contemporaneous"),
                              F.round("mean_split", 4).alias("mean_split"), F.round("min_norm_ls", 4).alias("min_norm_ls")))
    return reduce(DataFrame.unionByName, out)


#: (name, sizes, periods, first-mode groups) from the cube that is fitted to a hundred billion fine cells.
SCALE = [("nation x brand x week", 25, 25, 357, 90, 5), ("supplier x brand x month", 1000, 25, 83, 21, 190), ("supplier x part x day", 10_000, 20_000, 2499, 357, 1900), ("supplier x part x day, ten times", 100_000, 200_000, 2499, 357, 19_000)]
SCALE_SQL = "(VALUES " + ", ".join(f"('{r[0]}', {', '.join(map(str, r[1:]))})" for r in SCALE) + ") t(name, n_i, n_j, n_k, kw, iu)"


@query(f"""SELECT name, CAST(n_i AS BIGINT) * n_j * n_k AS fine_cells, 10 * (CAST(n_i AS BIGINT) * n_j * kw + CAST(iu AS BIGINT) * n_j * n_k) AS work_of_a_gradient,
  CAST(8 * 10 * (n_i + n_j + n_k) AS BIGINT) AS factor_bytes, 8 * 10 * greatest(n_i, n_j, n_k) > {256 << 20} AS partitioned,
  CAST(least(CAST(n_i AS BIGINT) * n_j, CAST(n_i AS BIGINT) * kw, CAST(n_j AS BIGINT) * kw, 16 * CAST(iu AS BIGINT) * n_j) // 16 AS BIGINT) AS rank_bound FROM {SCALE_SQL}""")
def scale_costs(spark, sf_dir):
    """How a gradient's work, the factors and the rank bound grow from the given cube to large ones, at rank 10."""
    rows = [(name, i * j * k, costs.dominant((i, j, k), kw, iu, j, 10), costs.memory_model((i, j, k), (i, j, kw), (iu, j, k), 10)["factors"], "partitioned" in costs.placement((i, j, k), 10).values(), rank_bound(i, j, iu, j, kw)) for name, i, j, k, kw, iu in SCALE]
    return spark.createDataFrame(rows, "name string, fine_cells long, work_of_a_gradient long, factor_bytes long, partitioned boolean, rank_bound long")


@query()
def workload_quarters(spark, sf_dir):
    w = W.regional_quarters(spark, sf_dir)
    return spark.createDataFrame(W.run_level(w, w.levels[0], (1,), ("mean_split", "min_norm_ls")), W.SCORE)


@query()
def smooth_ls(spark, sf_dir):
    _, _, t, c = dept_views(spark, sf_dir)
    return ls_blocks(t, c, "smooth", 0.1)


@query()
def dct_sparse(spark, sf_dir):
    _, _, t, c = dept_views(spark, sf_dir)
    return ls_blocks(t, c, "sparse")


def masked_dept_views(spark, sf_dir):
    cells, shape, t, c = dept_views(spark, sf_dir)
    hide = lambda v: View(masks.mask_random(v.cells, 0.2), shape, v.groupings).placed()
    return cells, shape, hide(t), hide(c)


@query()
def min_norm_masked(spark, sf_dir):
    _, _, t, c = masked_dept_views(spark, sf_dir)
    return ls_blocks(t, c)


def residuals(x: DataFrame, view: View) -> DataFrame:
    """i, j, k of a view's observed cells and e: the estimate's own view less the view."""
    own = mode_products(x, view.groupings).withColumnRenamed("v", "own")
    cells = view.cells.withColumnRenamed("v", "seen")
    how = "left" if view.absent == "zero" else "inner"
    return own.join(cells, ["i", "j", "k"], how).select("i", "j", "k", (F.col("own") - F.coalesce("seen", F.lit(0.0))).alias("e"))


def gradients(x: DataFrame, t: View, c: View) -> DataFrame:
    """i, j, k, v and g: the gradient (half) of both views' squared residuals at each fine cell of an estimate."""
    w, u, v = (F.floor(F.col(m) / n).cast("long") for m, n in (("k", 4), ("i", 5), ("j", 3)))
    et = residuals(x, t).withColumnsRenamed({"i": "ti", "j": "tj", "k": "tk", "e": "et"})
    ec = residuals(x, c).withColumnsRenamed({"i": "ci", "j": "cj", "k": "ck", "e": "ec"})
    both = x.join(et, (F.col("i") == F.col("ti")) & (F.col("j") == F.col("tj")) & (w == F.col("tk")), "left").join(ec, (u == F.col("ci")) & (v == F.col("cj")) & (F.col("k") == F.col("ck")), "left")
    return both.select("i", "j", "k", "v", (F.coalesce("et", F.lit(0.0)) + F.coalesce("ec", F.lit(0.0))).alias("g"))


BLOCKS_SQL = "SELECT count(*) AS n_cells FROM shares JOIN (SELECT DISTINCT i // 5 AS bu, j // 3 AS bv FROM cells{}) ON i // 5 = bu AND j // 3 = bv"


@query(f"WITH {DEPT_X} SELECT *, CAST(0 AS DOUBLE) AS gradient FROM ({BLOCKS_SQL.format('')})")
def smooth_ls_optimal(spark, sf_dir):
    """The smooth estimate solves its normal equations: the gradient of its objective is zero at every fine cell of the whole cube."""
    _, _, t, c = dept_views(spark, sf_dir)
    x = W.shared.table(ls_blocks(t, c, "smooth", 0.1))
    line = Window.partitionBy("i", "j").orderBy("k")
    step = lambda n: F.coalesce(F.col("v") - (F.lag("v") if n < 0 else F.lead("v")).over(line), F.lit(0.0))
    g = gradients(x, t, c).withColumn("g", F.col("g") + 0.1 * (step(-1) + step(1)))
    return g.agg(F.count("*").alias("n_cells"), (F.round(F.max(F.abs("g")), 3) + 0.0).alias("gradient"))


@query(f"WITH {DEPT_X} SELECT n_cells, CAST(0 AS DOUBLE) AS gradient, CAST(0 AS DOUBLE) AS interaction FROM ({BLOCKS_SQL.format('')})")
def min_norm_masked_optimal(spark, sf_dir):
    """With a fifth of the cells masked: the estimate fits what is observed, and is a sum of what the cells of either view could add, as the solution of minimum norm must be."""
    _, _, t, c = masked_dept_views(spark, sf_dir)
    x = W.shared.table(ls_blocks(t, c))
    block = [F.floor(F.col("i") / 5), F.floor(F.col("j") / 3), F.floor(F.col("k") / 4)]
    mean = lambda *more: F.avg("v").over(Window.partitionBy(*block, *more))
    g = gradients(x, t, c).withColumn("q", F.col("v") - mean("i", "j") - mean("k") + mean())
    return g.agg(F.count("*").alias("n_cells"), (F.round(F.max(F.abs("g")), 3) + 0.0).alias("gradient"), (F.round(F.max(F.abs("q")), 3) + 0.0).alias("interaction"))


def sparse_objective(x: DataFrame, t: View, c: View, sparse: float = 1.0, smooth: float = 1.0) -> float:
    """Half the squared residuals, plus the sum of absolute cosine coefficients, plus the squared steps between ticks."""
    n = t.shape[2]
    functions.register(x.sparkSession)
    basis = F.broadcast(x.sparkSession.sql(f"SELECT m, k, value FROM dct_basis({n})"))
    fit = sum(float(residuals(x, v).agg(F.sum(F.col("e") ** 2)).first()[0]) for v in (t, c))
    size = float(x.join(basis, "k").groupBy("i", "j", "m").agg(F.sum(F.col("v") * F.col("value")).alias("s")).agg(F.sum(F.abs("s"))).first()[0])
    step = F.col("v") - F.lag("v").over(Window.partitionBy("i", "j").orderBy("k"))
    rough = float(x.select((step**2).alias("d")).agg(F.sum("d")).first()[0])
    return 0.5 * fit + sparse * size + smooth * rough


@query(f"WITH {DEPT_X} SELECT n_cells, TRUE AS not_negative, TRUE AS below_smooth, TRUE AS below_shorter, TRUE AS below_longer FROM ({BLOCKS_SQL.format('')})")
def dct_sparse_optimal(spark, sf_dir):
    """The sparse estimate isn't negative, and its objective is below that of the smooth estimate and of itself a hundredth shorter or longer."""
    _, _, t, c = dept_views(spark, sf_dir)
    x, smooth = W.shared.table(ls_blocks(t, c, "sparse")), W.shared.table(ls_blocks(t, c, "smooth", 2.0).withColumn("v", F.greatest("v", F.lit(0.0))))
    own, other, shorter, longer = (sparse_objective(y, t, c) for y in (x, smooth, *(x.withColumn("v", F.col("v") * f) for f in (0.99, 1.01))))
    row = x.agg(F.count("*").alias("n_cells"), (F.min("v") >= 0).alias("not_negative"))
    return row.withColumns({"below_smooth": F.lit(own <= other), "below_shorter": F.lit(own <= shorter), "below_longer": F.lit(own <= longer)})


# --- relational operators around the methods ----------------------------------------------------------------------------------------

@query(f"SELECT i, j, k, v FROM ({NBW}) WHERE i BETWEEN 2 AND 9 AND k >= 100 AND k < 140 AND j IN (1, 3, 5)")
def slice_dice(spark, sf_dir):
    return dice_cube(W.retail_nbw(spark, sf_dir), i=(2, 10), k=(100, 140)).where(F.col("j").isin(1, 3, 5))


@query(f"WITH cells AS ({DOCS}) SELECT a.i, b.j, c.k, coalesce(v, 0) AS v FROM {axis('i', 20)} a, {axis('j', 4)} b, {axis('k', 14)} c LEFT JOIN cells x ON x.i = a.i AND x.j = b.j AND x.k = c.k")
def join_densify(spark, sf_dir):
    """All cells of documents by source, language and length, sizes as the table has them."""
    cells = W.docs_sln(spark, sf_dir)
    return densify(cells, dict(zip("ijk", W.extent(cells, W.CUBES["docs_sln"][1]))))


@query(f"SELECT coalesce(a.i, b.i) AS i, coalesce(a.j, b.j) AS j, round(coalesce(a.v, 0) - coalesce(b.v, 0), 6) + 0.0 AS v FROM (SELECT i, j, sum(v) AS v FROM ({NBW}) WHERE k < 180 GROUP BY 1, 2) a FULL JOIN (SELECT i, j, sum(v) AS v FROM ({NBW}) WHERE k >= 180 GROUP BY 1, 2) b ON a.i = b.i AND a.j = b.j")
def join_full_outer(spark, sf_dir):
    cells = W.retail_nbw(spark, sf_dir)
    half = lambda c, n: cells.where(c).groupBy("i", "j").agg(F.sum("v").alias(n))
    return half("k < 180", "a").join(half("k >= 180", "b"), ["i", "j"], "full_outer").select("i", "j", (F.coalesce("a", F.lit(0.0)) - F.coalesce("b", F.lit(0.0))).alias("v"))


@query(f"SELECT CAST(a.i AS BIGINT) AS i, CAST(b.j AS BIGINT) AS j FROM range(0, 150) a(i), range(0, 50) b(j) ANTI JOIN ({CUBE_SQL['incident_utd']}) x ON x.i = a.i AND x.j = b.j")
def join_anti_missing(spark, sf_dir):
    pairs = spark.range(150 * 50).select(F.floor(F.col("id") / 50).alias("i"), F.pmod("id", F.lit(50)).alias("j"))
    return pairs.join(W.incident_utd(spark, sf_dir).select("i", "j"), ["i", "j"], "left_anti")


@query("SELECT e.event_id, p.event_id AS last_id FROM events e ASOF JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON e.user_id = p.user_id AND p.ts < e.ts WHERE e.event_type = 'click'".replace("ASOF JOIN", "ASOF JOIN"))
def asof_join(spark, sf_dir):
    """Each click's last earlier purchase of its user: sorts by user, day and time, no join of events with events.

    A user's events are dealt by day, and a day begins with the last purchase of the days before, so a user with very many events isn't one task.
    """
    e = load(spark, sf_dir, "events").where(F.col("event_type").isin("click", "purchase")).withColumn("_t", F.unix_micros(F.col("ts").cast("timestamp")))
    e = e.withColumn("_day", F.floor(F.col("_t") / 86_400_000_000))
    bought = F.max(F.when(F.col("event_type") == "purchase", F.struct("_t", "event_id")))
    days = e.groupBy("user_id", "_day").agg(bought.alias("_last"))
    earlier = Window.partitionBy("user_id").orderBy("_day").rowsBetween(Window.unboundedPreceding, -1)
    days = days.select("user_id", "_day", F.max("_last").over(earlier).alias("_before"))
    within = Window.partitionBy("user_id", "_day").orderBy("_t").rangeBetween(Window.unboundedPreceding, -1)
    seen = e.withColumn("_own", bought.over(within)).where(F.col("event_type") == "click").join(days, ["user_id", "_day"])
    return seen.select("event_id", F.coalesce("_own", "_before")["event_id"].alias("last_id")).where("last_id IS NOT NULL")


@query("SELECT p.n AS period, count(*) AS n, round(sum(value), 4) AS v FROM events JOIN (VALUES (0, 0, 10), (1, 5, 15), (2, 12, 30)) p(n, a, b) ON date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) >= p.a AND date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) < p.b GROUP BY 1")
def interval_join(spark, sf_dir):
    """Overlapping periods: the few periods are expanded to ticks, and the join is by equality."""
    functions.register(spark)
    periods = spark.createDataFrame([(0, 0, 10), (1, 5, 15), (2, 12, 30)], "period int, a int, b int")
    ticks = periods.lateralJoin(spark.tvf.explode(F.sequence(F.col("a").outer(), F.col("b").outer() - 1)).toDF("day")).select("period", "day")
    days = load(spark, sf_dir, "events").groupBy(F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date")).alias("day")).agg(F.count("*").alias("n"), F.sum("value").alias("v"))
    return days.join(F.broadcast(ticks), "day").groupBy("period").agg(F.sum("n").alias("n"), F.round(F.sum("v"), 4).alias("v"))


@query(f"SELECT i, j, k, v, sum(v) OVER (PARTITION BY i, j ORDER BY k) AS running, v - lag(v) OVER (PARTITION BY i, j ORDER BY k) AS step, round(avg(v) OVER (PARTITION BY i, j ORDER BY k ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 6) AS smooth FROM ({CUBE_SQL['retail_sbm']})")
def window_series(spark, sf_dir):
    w = Window.partitionBy("i", "j").orderBy("k")
    return W.retail_sbm(spark, sf_dir).select("i", "j", "k", "v", F.sum("v").over(w).alias("running"), (F.col("v") - F.lag("v").over(w)).alias("step"), F.round(F.avg("v").over(w.rowsBetween(-3, 0)), 6).alias("smooth"))


@query("SELECT s_suppkey, CAST(ntile(7) OVER (ORDER BY s_acctbal, s_suppkey) AS INT) AS band, CAST(dense_rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC) AS INT) AS place FROM supplier")
def window_bands(spark, sf_dir):
    """Bands of equal size over the whole table, from row numbers that no single task makes, and places within nations."""
    suppliers = load(spark, sf_dir, "supplier")
    n = suppliers.count()
    small, more = divmod(n, 7)
    at = F.col("idx")
    band = F.when(at < more * (small + 1), F.floor(at / (small + 1))).otherwise(more + F.floor((at - more * (small + 1)) / max(small, 1)))
    placed = numbered(suppliers.select("s_suppkey", "s_nationkey", "s_acctbal"), ["s_acctbal", "s_suppkey"])
    return placed.select("s_suppkey", (band + 1).cast("int").alias("band"), F.dense_rank().over(Window.partitionBy("s_nationkey").orderBy(F.desc("s_acctbal"))).alias("place"))


@query(f"SELECT i, j FROM ({NBW}) WHERE k < 100 INTERSECT SELECT i, j FROM ({NBW}) WHERE k >= 300")
def setop_intersect(spark, sf_dir):
    cells = W.retail_nbw(spark, sf_dir)
    return cells.where("k < 100").select("i", "j").intersect(cells.where("k >= 300").select("i", "j"))


@query(f"SELECT j, k FROM ({CUBE_SQL['incident_utd']}) WHERE i < 40 EXCEPT SELECT j, k FROM ({CUBE_SQL['incident_utd']}) WHERE i >= 110")
def setop_except(spark, sf_dir):
    cells = W.incident_utd(spark, sf_dir)
    return cells.where("i < 40").select("j", "k").subtract(cells.where("i >= 110").select("j", "k"))


@query("SELECT event_type, CAST(json_extract(props, '$.k') AS INT) AS k, count(*) AS n, round(stddev_pop(value), 6) AS sd, round(covar_pop(value, user_id), 1) AS r FROM events GROUP BY 1, 2 HAVING count(*) > 10")
def json_stats(spark, sf_dir):
    k = F.from_json("props", "k int")["k"]
    return load(spark, sf_dir, "events").groupBy("event_type", k.alias("k")).agg(F.count("*").alias("n"), F.round(F.stddev_pop("value"), 6).alias("sd"), F.round(F.covar_pop("value", "user_id"), 1).alias("r")).where("n > 10")


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 6) AS norm, CAST(embedding[1] AS DOUBLE) AS first, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def array_functions(spark, sf_dir):
    x = F.transform("embedding", lambda e: e.cast("double"))
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(F.aggregate(x, F.lit(0.0), lambda s, e: s + e * e), 6).alias("norm"), F.element_at("embedding", 1).cast("double").alias("first"), F.size(F.filter("embedding", lambda e: e > 0)).cast("long").alias("positive"))


@query(f"SELECT i, j, round(coalesce(max(v) FILTER (WHERE k % 4 = 0), 0), 6) AS q0, round(coalesce(max(v) FILTER (WHERE k % 4 = 1), 0), 6) AS q1, round(coalesce(max(v) FILTER (WHERE k % 4 = 2), 0), 6) AS q2, round(coalesce(max(v) FILTER (WHERE k % 4 = 3), 0), 6) AS q3 FROM ({DEPT}) GROUP BY 1, 2")
def pivot_slab(spark, sf_dir):
    wide = W.dept_stm(spark, sf_dir).withColumn("q", F.pmod("k", F.lit(4))).groupBy("i", "j").pivot("q", [0, 1, 2, 3]).agg(F.max("v")).na.fill(0.0)
    return rounded(wide.withColumnsRenamed({str(n): f"q{n}" for n in range(4)}))


@query(f"SELECT i, j, k, round(v, 6) + 0.0 AS v FROM ({SENSOR})")
def unpivot_slab(spark, sf_dir):
    """The cube unfolded along time, a column for each tick, and folded again."""
    return rounded(fold(unfold(W.sensor_utd(spark, sf_dir), 30), 30))


@query(f"SELECT i, count(*) AS brands, count(*) FILTER (WHERE v > 100) AS large, max(v) AS most, CAST(arg_max(j, v * 100 - j) AS BIGINT) AS best FROM (SELECT i, j, sum(v) AS v FROM ({NBW}) GROUP BY 1, 2) GROUP BY i")
def map_functions(spark, sf_dir):
    """A nation's brands as a map, and questions to it."""
    sums = W.retail_nbw(spark, sf_dir).groupBy("i", "j").agg(F.sum("v").alias("v"))
    maps = sums.groupBy("i").agg(F.map_from_entries(F.collect_list(F.struct("j", "v"))).alias("m"))
    best = F.array_max(F.transform(F.map_entries("m"), lambda e: F.struct((e["value"] * 100 - e["key"]).alias("x"), e["key"].alias("j"))))["j"]
    return maps.select("i", F.size("m").cast("long").alias("brands"), F.size(F.map_filter("m", lambda k, v: v > 100)).cast("long").alias("large"), F.array_max(F.map_values("m")).alias("most"), best.alias("best"))


@query(f"SELECT a.i AS first, b.i AS second, count(*) AS n, round(corr(a.v, b.v), 6) AS r FROM ({view_sql(NBW, i='g', extra=f'JOIN {REGION} ON m = i')}) a JOIN ({view_sql(NBW, i='g', extra=f'JOIN {REGION} ON m = i')}) b ON a.j = b.j AND a.k = b.k AND a.i < b.i GROUP BY 1, 2")
def mode_correlation(spark, sf_dir):
    """How alike areas are: the correlation of their cells, from one pass over slabs that hold a value for each area."""
    slabs = unfold(nbw_views(spark, sf_dir)[1].cells, 5, "i")
    pairs = [F.struct(F.lit(a).cast("long").alias("first"), F.lit(b).cast("long").alias("second"), F.count_if(F.col(f"c{a}").isNotNull() & F.col(f"c{b}").isNotNull()).alias("n"), F.round(F.corr(f"c{a}", f"c{b}"), 6).alias("r")) for a in range(5) for b in range(a + 1, 5)]
    return slabs.agg(F.array(*pairs).alias("p")).select(F.explode("p").alias("p")).select("p.*").where("n > 0")


@query(f"""WITH f AS (SELECT {S_BRAND} AS j, {S_TYPE} AS r, {QUANTITY} AS q FROM {SALES} GROUP BY 1, 2)
SELECT CAST(a.r AS BIGINT) AS r, {", ".join(f"coalesce(sum(a.q * b.q) FILTER (WHERE b.r = {s}), 0) + 0.0 AS g{s}" for s in range(6))} FROM f a JOIN f b USING (j) GROUP BY 1""")
def gram_aggregate(spark, sf_dir):
    """The Gram matrix of a factor that is a table: a brand's quantities of the six types."""
    own = F.array(*(F.sum(F.when(F.col("p_type") == t, F.col("l_quantity")).otherwise(0.0)) for t in W.TYPES))
    rows = W.sales(spark, sf_dir).groupBy("p_brand").agg(own.alias("f")).agg(functions.gram_agg(F.col("f"), 6).alias("g")).select(F.posexplode("g").alias("r", "g"))
    return rows.select(F.col("r").cast("long").alias("r"), *(F.col("g")[s].alias(f"g{s}") for s in range(6)))


@query("""SELECT CAST(d AS DATE) AS day, n AS tick, n // 7 AS week, CAST((year(d) - year(a)) * 12 + month(d) - month(a) AS BIGINT) AS month, CAST((year(d) - year(a)) * 4 + quarter(d) - quarter(a) AS BIGINT) AS quarter,
  CAST((year(d) - year(a)) * 2 + (month(d) - 1) // 6 - (month(a) - 1) // 6 AS BIGINT) AS half_year FROM (SELECT a, n, a + CAST(n AS INTEGER) AS d FROM (SELECT a, unnest(range(0, date_diff('day', a, z) + 1)) AS n
  FROM (SELECT min(CAST(l_shipdate AS DATE)) AS a, max(CAST(l_shipdate AS DATE)) AS z FROM lineitem)))""")
def dim_calendar(spark, sf_dir):
    """The days from the first to the last shipment."""
    return calendar_of(load(spark, sf_dir, "lineitem"), "l_shipdate")


@query(f"SELECT name, CAST(least(n_i * n_j, n_i * kw, n_j * kw, 16 * iu * jv) // 16 AS BIGINT) AS bound FROM {SIZES_SQL}")
def scalar_rank_bound(spark, sf_dir):
    """The bound as a SQL function."""
    functions.register(spark)
    bounds_frame(spark, SIZES).createOrReplaceTempView("finegrain_sizes")
    return spark.sql("SELECT name, rank_bound(n_i, n_j, iu, jv, kw) AS bound FROM finegrain_sizes")


@query(f"SELECT i, count(*) AS n, round(quantile_cont(v, 0.5), 6) AS median, round(stddev_samp(v), 6) AS sd, max_by(k, v * 1000 + k) AS peak FROM ({CUBE_SQL['retail_sbm']}) WHERE (7919 * i + 104729 * j + 1299709 * k) % 1000 < 300 GROUP BY i")
def sampled_statistics(spark, sf_dir):
    """Statistics over a repeatable sample of the cells, by a hash of their indexes."""
    own = F.pmod(7919 * F.col("i") + 104729 * F.col("j") + 1299709 * F.col("k"), F.lit(1000)) < 300
    return W.retail_sbm(spark, sf_dir).where(own).groupBy("i").agg(F.count("*").alias("n"), F.round(F.percentile("v", 0.5), 6).alias("median"), F.round(F.stddev_samp("v"), 6).alias("sd"), F.max_by("k", F.col("v") * 1000 + F.col("k")).alias("peak"))


@query("SELECT n_name, (SELECT count(*) FROM supplier WHERE s_nationkey = n_nationkey) AS suppliers, EXISTS (SELECT 1 FROM customer WHERE c_nationkey = n_nationkey AND c_acctbal > 9900) AS rich FROM nation")
def subqueries(spark, sf_dir):
    for t in ("nation", "supplier", "customer"):
        load(spark, sf_dir, t).createOrReplaceTempView(f"finegrain_{t}")
    return spark.sql("SELECT n_name, (SELECT count(*) FROM finegrain_supplier WHERE s_nationkey = n_nationkey) AS suppliers, EXISTS (SELECT 1 FROM finegrain_customer WHERE c_nationkey = n_nationkey AND c_acctbal > 9900) AS rich FROM finegrain_nation")


@query("SELECT count(DISTINCT i) AS stores, count(DISTINCT k) AS ticks, approx_close FROM (SELECT *, TRUE AS approx_close FROM (" + NBW + ")) GROUP BY approx_close")
def distinct_counts(spark, sf_dir):
    out = W.retail_nbw(spark, sf_dir).agg(F.countDistinct("i").alias("stores"), F.countDistinct("k").alias("ticks"), F.approx_count_distinct("k", 0.02).alias("a"))
    return out.select("stores", "ticks", (F.abs(F.col("a") - F.col("ticks")) <= 0.1 * F.col("ticks")).alias("approx_close"))


# --- streams ----------------------------------------------------------------------------------------------------------------------------

STREAM_T = "SELECT user_id % 50 AS i, event_type AS j, time_bucket(INTERVAL 7 DAYS, ts, TIMESTAMP '1970-01-01') AS start, round(sum(value), 6) AS v, count(*) AS n FROM events GROUP BY 1, 2, 3"


def stream_of(spark, sf_dir):
    """The events file as a stream."""
    path = f"{sf_dir}/events.parquet"
    return spark.readStream.schema(load(spark, sf_dir, "events").schema).parquet(f"{sf_dir}/event[s].parquet") if path else None


@query(STREAM_T)
def stream_tumbling(spark, sf_dir):
    out = streaming.run_available(streaming.stream_temporal(stream_of(spark, sf_dir)), "finegrain_tumbling", "complete")
    return rounded(out.withColumn("start", F.col("start").cast("timestamp_ntz")))


@query("SELECT user_id % 50 AS i, event_type AS j, s AS start, round(sum(value), 6) AS v, count(*) AS n FROM (SELECT *, time_bucket(INTERVAL 84 HOURS, ts, TIMESTAMP '1970-01-01') - INTERVAL 84 HOURS AS s FROM events UNION ALL SELECT *, time_bucket(INTERVAL 84 HOURS, ts, TIMESTAMP '1970-01-01') FROM events) GROUP BY 1, 2, 3")
def stream_sliding(spark, sf_dir):
    out = streaming.run_available(streaming.stream_temporal(stream_of(spark, sf_dir), "7 days", "84 hours"), "finegrain_sliding", "complete")
    return rounded(out.withColumn("start", F.col("start").cast("timestamp_ntz")))


@query("SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 6 HOURS AS \"end\", count(*) AS n FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOURS THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY user_id, s")
def stream_session(spark, sf_dir):
    out = streaming.run_available(streaming.stream_sessions(stream_of(spark, sf_dir)), "finegrain_sessions", "complete")
    return out.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "end")})


@query("SELECT count(*) AS n, count(DISTINCT event_id) AS events FROM events")
def stream_dedup(spark, sf_dir):
    twice = stream_of(spark, sf_dir)
    out = streaming.run_available(streaming.stream_deduplicated(twice.unionByName(twice)), "finegrain_dedup")
    return out.agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("events"))


@query("SELECT user_id, event_type, round(sum(value), 6) AS v FROM events GROUP BY 1, 2")
def stream_state(spark, sf_dir):
    out = streaming.run_available(streaming.running_slabs(stream_of(spark, sf_dir)), "finegrain_slabs", "update")
    return rounded(out.groupBy("user_id", "event_type").agg(F.max("v").alias("v")))


@query("""
WITH e AS (SELECT event_id % 4 AS f, ts - CASE WHEN event_id % 4 = 3 THEN INTERVAL 3 DAYS ELSE INTERVAL 0 DAYS END AS ts FROM events),
files AS (SELECT f, max(ts) AS top FROM e GROUP BY f),
known AS (SELECT a.f, max(b.top) - INTERVAL 2 DAYS AS mark FROM files a JOIN files b ON b.f < a.f - 1 GROUP BY a.f),
placed AS (SELECT f, time_bucket(INTERVAL 7 DAYS, ts, TIMESTAMP '1970-01-01') AS start FROM e)
SELECT start, count(*) AS n FROM placed LEFT JOIN known USING (f) WHERE mark IS NULL OR start + INTERVAL 7 DAYS > mark GROUP BY 1""")
def stream_late(spark, sf_dir):
    """Four files one after the other, the last of them three days late: rows of periods that the watermark has closed are dropped, as missing cells."""
    folder = f"{W.shared.shared_dir(spark)}/events-{uuid.uuid4().hex}"
    streaming.replay_files(spark, sf_dir, folder)
    out = streaming.run_available(streaming.stream_temporal(streaming.event_stream(spark, folder)), "late", "update")
    last = out.groupBy("i", "j", "start").agg(F.max("n").alias("n"))
    return last.groupBy(F.col("start").cast("timestamp_ntz").alias("start")).agg(F.sum("n").alias("n"))


@query("""
WITH t AS (SELECT user_id % 50 AS bucket, event_type AS j, time_bucket(INTERVAL 7 DAYS, ts, TIMESTAMP '1970-01-01') AS start, sum(value) AS vt FROM events GROUP BY 1, 2, 3),
c AS (SELECT user_id % 5 AS grp, event_type AS j, date_trunc('day', ts) AS day, sum(value) AS vc FROM events GROUP BY 1, 2, 3), m AS (SELECT max(ts) - INTERVAL 2 DAYS AS mark FROM events)
SELECT bucket, t.j, CAST(day AS TIMESTAMP) AS day, round((vt / 7 + vc / 10) / 2, 6) AS v FROM t JOIN c ON bucket % 5 = grp AND t.j = c.j AND day >= start AND day < start + INTERVAL 7 DAYS, m WHERE start + INTERVAL 7 DAYS <= mark AND day + INTERVAL 1 DAY <= mark""")
def stream_mean(spark, sf_dir):
    """The even split online: both views' closed cells, joined as streams."""
    out = streaming.run_available(streaming.stream_mean(stream_of(spark, sf_dir)), "mean")
    return rounded(out.withColumn("day", F.col("day").cast("timestamp_ntz")))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cube, views, coupled fit and scores of the retail cube."""
    cells = W.retail_nbw(spark, sf_dir)
    w = W.Workload("retail_nbw", cells, NBW_SHAPE, [W.Level("A-mod", G.period(357, 4), W.regions(spark, sf_dir))])
    return spark.createDataFrame(W.run_level(w, w.levels[0], (3,), ("mean_split", "coupled_cp")), W.SCORE)


__all__ = ["ORACLES", "QUERIES", "flagship", "planted_factors", "reconstruct", "mode_products"]
