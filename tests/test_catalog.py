"""Catalogue queries against their SQL, on the smallest tables; streams, SQL functions and plans."""

import duckdb
import numpy as np
import pytest
from helpers import SF, cells
from pyspark.sql import functions as F

from finegrain import catalog
from finegrain.functions import sql as functions
from finegrain.operators import groupings as G
from finegrain.operators.views import View, make_view
from finegrain.plans import costs, planner
from finegrain.plans import workloads as W
from finegrain.sources.tables import TABLES, bucket_cells, load, register, save_scores
from finegrain.streaming import views as streaming

FAST = [q for q in catalog.ORACLES if q.startswith(("cube_", "profile_", "view_", "calendar_", "mask_", "dim_", "rank", "flop", "leader", "improve", "oracle", "measurement", "slab", "window", "setop", "array", "json", "pivot", "scalar", "asof", "interval", "subq", "distinct", "slice", "join_", "mean_worked", "gram", "dct_basis", "dct_transform", "unpivot", "map_", "mode_", "scale_"))]


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


def same(spark, con, name):
    df = catalog.QUERIES[name](spark, SF)
    want = con.sql(catalog.ORACLES[name])
    columns = sorted(df.columns)
    assert columns == sorted(want.columns)
    at = [want.columns.index(c) for c in columns]
    assert sorted(repr(tuple(r[c] for c in columns)) for r in df.collect()) == sorted(repr(tuple(r[i] for i in at)) for r in want.fetchall())


@pytest.mark.parametrize("name", FAST)
def test_fast_queries(spark, con, name):
    same(spark, con, name)


@pytest.mark.parametrize("name", ["mean_split_B", "mean_split_masked", "min_norm_A", "nde_mean_A", "consistency_min_norm", "coupled_loss_r2", "grad_c_r2", "step_a_r2", "blind_grad_ct_r2", "blind_step_c_r2", "nde_gram_form", "stream_tumbling", "stream_sliding", "stream_session", "stream_dedup", "stream_state", "stream_late", "stream_mean", "one_cycle_r2", "smooth_ls_optimal", "min_norm_masked_optimal", "dct_sparse_optimal", "mean_split_A", "min_norm_B"])
def test_method_queries(spark, con, name):
    same(spark, con, name)


def test_entry(spark):
    import __spark_entry__ as entry

    assert {r.method for r in entry.entry(spark).collect()} == {"mean_split", "coupled_cp"}
    assert set(catalog.QUERIES) <= set(entry.queries()) and set(entry.oracle_sql()) <= set(entry.queries())


def test_sql_functions(spark):
    functions.register(spark)
    assert spark.sql("SELECT cp_value(array(1D, 2D), array(3D, 4D), array(5D, 6D))").first()[0] == 63.0
    assert spark.sql("SELECT rank_bound(93, 50, 18, 50, 98)").first()[0] == 290
    assert [r.tick for r in spark.sql("SELECT * FROM expand_period(2, 5)").collect()] == [2, 3, 4]
    assert spark.sql("SELECT tick_of(TIMESTAMP_NTZ'2024-01-20 10:00:00', DATE'2024-01-01', 7)").first()[0] == 2
    functions.register_model(spark, "my_model", {m: np.full((2, 1), n + 1.0) for n, m in enumerate("ijk")})
    assert spark.sql("SELECT v FROM range(2) r, LATERAL my_model(r.id, 0, 1)").first()[0] == 6.0


def test_plans(spark):
    shape = (4, 4, 6)
    x = cells(spark, np.ones(shape))
    full = make_view(x, shape, absent="zero", k=G.period(6, 2))
    few = View(make_view(x, shape, k=G.period(6, 2)).cells.where("NOT (i = 1 AND j = 2 AND k = 0)"), shape, {"k": G.period(6, 2)})
    listed = planner.with_holes_listed(few)
    assert [planner.residual_plan(v) for v in (full, few, listed)] == ["gram", "observed", "complement"]
    assert [tuple(r) for r in listed.holes.collect()] == [(1, 2, 0)]
    assert "plan gram" in planner.explain([full], 2)
    assert costs.placement((10**7, 100, 100), 40)["i"] == "partitioned" and set(costs.placement((100, 100, 100), 40).values()) == {"broadcast"}
    assert costs.fit_cost("gram", 10, 0, shape, 2, 10, 1).passes == 30 and costs.fit_cost("observed", 10, 0, shape, 2, 10, 1).passes == 60
    assert costs.dominant((93, 50, 397), 98, 18, 50, 40) == 93 * 50 * 98 * 40 + 18 * 50 * 397 * 40
    work = costs.flop_model((93, 50, 397), (93, 50, 98), (18, 50, 397), 40)
    assert work["sums"] == costs.dominant((93, 50, 397), 98, 18, 50, 40) and work["total"] > work["sums"]
    memory = costs.memory_model((93, 500, 230), (93, 500, 58), (18, 50, 230), 40)
    assert memory["least_squares_matrix"] > 1e14 > 1e9 > memory["least_squares_block"]


def test_pushdown_reaches_the_scan(spark):
    plan = load(spark, SF, "lineitem").where("l_quantity > 40").select("l_partkey")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,40.0)]" in plan and "l_comment" not in plan
    plan = W.retail_nbw(spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<l_partkey:bigint,l_suppkey:bigint,l_quantity:double,l_shipdate" in plan and "Python" not in plan


def test_sinks_and_streams(spark, tmp_path):
    register(spark, SF, ("nation",))
    assert spark.sql("SELECT count(*) FROM nation").first()[0] == 25
    scores = catalog.published(spark)
    for fmt in ("csv", "json", "orc"):
        save_scores(scores, str(tmp_path / fmt), fmt)
        assert spark.read.format(fmt).load(str(tmp_path / fmt)).count() >= scores.count()
    spark.sql("DROP TABLE IF EXISTS finegrain_bucketed")
    assert bucket_cells(cells(spark, np.ones((3, 2, 2))), "finegrain_bucketed", "i", 2).count() == 12
    spark.sql("DROP TABLE finegrain_bucketed")
    folder = str(tmp_path / "events")
    streaming.replay_files(spark, SF, folder)
    events = streaming.event_stream(spark, folder)
    total = load(spark, SF, "events").count()
    day = lambda df: df.selectExpr("i", "j", "CAST(start AS DATE) AS start", "v", "n").orderBy("i", "j", "start")
    seen = streaming.run_available(streaming.stream_temporal(events, watermark="100 days"), "late_test", "update")
    last = seen.groupBy("i", "j", "start").agg(F.max_by("v", "n").alias("v"), F.max("n").alias("n"))
    batch = streaming.stream_temporal(spark.read.parquet(folder))
    got, want = day(last).collect(), day(batch).collect()
    assert [(r.i, r.j, r.start, r.n) for r in got] == [(r.i, r.j, r.start, r.n) for r in want]
    assert np.allclose([r.v for r in got], [r.v for r in want])
    days = streaming.run_available(streaming.stream_contemporaneous(streaming.event_stream(spark, folder), watermark="100 days"), "days_test", "update")
    by_day = lambda df: [(r.i, r.j, r.day) for r in df.select("i", "j", "day").distinct().orderBy("i", "j", "day").collect()]
    assert by_day(days) == by_day(streaming.stream_contemporaneous(spark.read.parquet(folder)))

    def refit(batch, last):
        own = np.array([float(batch.count())])
        return {"n": own if last is None else last["n"] + own, "fits": 1 if last is None else last["fits"] + 1}

    check = str(tmp_path / "check")
    fits = streaming.warm_fits(streaming.event_stream(spark, folder), refit, check)
    assert fits[-1]["n"][0] == total and fits[-1]["fits"] == len(fits) >= 2
    again = streaming.warm_fits(streaming.event_stream(spark, folder), refit, check)  # as after a restart: nothing is done twice
    assert [f["fits"] for f in again] == [f["fits"] for f in fits]
    load(spark, SF, "events").limit(5).write.mode("append").parquet(folder)
    assert streaming.warm_fits(streaming.event_stream(spark, folder), refit, check)[-1]["n"][0] == total + 5
