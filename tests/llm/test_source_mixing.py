import math

import numpy as np
import pytest
from llm_helpers import SF, table

from finegrain.llm import source_mixing as sm


def test_mean_counts_follow_the_weights(spark):
    rows = [(i, "x" * (10 + i % 7), "hot" if i % 3 else f"s{i % 5}") for i in range(6000)]
    docs = table(spark, rows, "doc_id long, text string, source string")
    weights = {"hot": 0.5, "s0": 0.3, "s3": 0.2, "s1": 0.0}
    rates = {r._source: r for r in sm.source_rates(docs, weights).collect()}
    out = sm.mix(docs, weights).groupBy("source").agg({"*": "count", "rate": "max"}).collect()
    size = {}
    for _, _, s in rows:
        size[s] = size.get(s, 0) + 1
    for r in out:
        want = rates[r.source]._rate * size[r.source]
        assert abs(r["count(1)"] - want) < 6 * math.sqrt(want)
    assert {r.source for r in out} == {"hot", "s0", "s3"}
    total = sum(len(t) for _, t, _ in rows)
    mixed = sm.mix(docs, weights).selectExpr("sum(length(text))").first()[0]
    assert abs(mixed - total) < 0.1 * total


def test_cdf_inverts_poisson():
    for rate in (0.0, 0.01, 1.0, 7.5, 120.0):
        cdf = np.array(sm.poisson_cdf(rate))
        want = np.cumsum([math.exp(k * math.log(rate) - rate - math.lgamma(k + 1)) if rate else float(k == 0) for k in range(len(cdf))])
        assert np.allclose(cdf, want) and cdf[-1] > 1 - 1e-12


def test_same_on_any_layout_and_shuffled(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    one = [(r.doc_id, r.copy) for r in sm.mix(docs).collect()]
    two = [(r.doc_id, r.copy) for r in sm.mix(docs.repartition(7)).collect()]
    assert one == two and one != sorted(one)
    assert all(copy == 0 or (i, copy - 1) in set(one) for i, copy in one)


def test_edges(spark):
    rows = [(None, None, None, 1.0), (1, "", "a", 1.0), (2, "text", "a", 1.0), (2, "text", "a", 1.0), (3, "é" * 50, None, 1.0)]
    docs = table(spark, rows, "doc_id long, text string, source string, rate double")
    out = sm.mix(docs, epochs=20.0).collect()
    ids = [r.doc_id for r in out]
    assert set(ids) == {None, 1, 2, 3} and ids.count(2) % 2 == 0
    assert sm.mix(table(spark, [], "doc_id long, text string, source string")).collect() == []
    with pytest.raises(ValueError):
        sm.mix(docs, epochs=10_000.0)
