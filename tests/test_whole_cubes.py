"""Queries whose cube outgrows the sizes it has at sf0.01."""

import pytest
from helpers import SF

from finegrain import catalog


@pytest.fixture
def wide(spark, monkeypatch):
    """117 suppliers, the last group of five not full; the months go on to 85."""
    rows = [(i, j, (7 * i + 13 * j + 5 * n) % 85, float(1 + (i + j + n) % 9)) for i in range(117) for j in range(6) for n in range(3)] + [(116, 5, 84, 1000.0)]
    cells = spark.createDataFrame(rows, "i long, j long, k long, v double").groupBy("i", "j", "k").sum("v").toDF("i", "j", "k", "v")
    monkeypatch.setattr(catalog.W, "dept_qtm", lambda spark, sf_dir: cells)
    return cells


def test_suppliers_beyond_the_hundredth(spark, wide):
    total = wide.agg({"v": "sum"}).first()[0]
    for name in ("mean_split_B", "min_norm_B"):
        row = catalog.QUERIES[name](spark, SF).selectExpr("count(*)", "sum(v)").first()
        assert row[0] == 117 * 6 * 85 and abs(row[1] - total) < 1
    blocks = {(r.i, r.j, r.k): r.v for r in catalog.QUERIES["min_norm_blocks"](spark, SF).collect()}
    closed = catalog.QUERIES["min_norm_B"](spark, SF).where("abs(v) > 0.02").collect()
    assert all(abs(blocks[r.i, r.j, r.k] - r.v) < 0.02 for r in closed) and max(i for i, _, _ in blocks) == 116
    assert (116, 5, 84) in {(r.i, r.j, r.k) for r in catalog.QUERIES["worst_cells"](spark, SF).collect()}


def test_documents_longer_than_fourteen_bands(spark, monkeypatch):
    cells = spark.createDataFrame([(0, 0, 0, 2.0), (19, 3, 15, 7.0), (20, 1, 3, 5.0)], "i long, j long, k long, v double")
    monkeypatch.setattr(catalog.W, "docs_sln", lambda spark, sf_dir: cells)
    row = catalog.QUERIES["join_densify"](spark, SF).selectExpr("count(*)", "sum(v)", "max(i)", "max(k)").first()
    assert tuple(row) == (21 * 4 * 16, 14.0, 20, 15)
