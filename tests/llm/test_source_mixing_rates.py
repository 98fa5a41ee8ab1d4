"""Sources whose rate is large, and many sources: nothing is refused, and the counts are those of the distribution."""

import hashlib
import math

import numpy as np
import pytest
from llm_helpers import table

from finegrain.llm import source_mixing as sm


def uniform(doc_id, text):
    digest = hashlib.md5(f"{sm.SEED}|{doc_id}|{hashlib.md5(text.encode()).hexdigest()}".encode()).hexdigest()
    return (int(digest[:13], 16) + 0.5) / 2**52


def count(rate, u):
    """By sums of exact logarithms from 0."""
    total, k = 0.0, -1
    while total <= u:
        k += 1
        total += math.exp(k * math.log(rate) - rate - math.lgamma(k + 1))
    return k


@pytest.fixture
def docs(spark):
    rows = [(i, "word " * 20_000, f"s{i % 20}") for i in range(200)] + [(1000, None, None), (1001, "tiny", "own")]
    return table(spark, rows, "doc_id long, text string, source string")


def test_one_row_source_beside_a_large_table(docs):
    rates = {r._source: r._rate for r in sm.source_rates(docs).collect()}
    assert rates[None] > 900 and rates["own"] > 450
    found = {r.doc_id: r for r in sm.mix(docs).groupBy("doc_id").agg({"copy": "count", "copies": "max", "rate": "max"}).collect()}
    for i, text, source in [(1000, "", None), (1001, "tiny", "own")]:
        assert found[i]["count(copy)"] == found[i]["max(copies)"] == count(rates[source], uniform(i, text))


def test_window_meets_the_small_table():
    for rate in (500.5, 600.0, 690.3):
        first, cdf = sm.poisson_window(rate)
        whole = np.array(sm.poisson_cdf(rate))
        assert first > 0 and whole[first - 1] < 1e-20 and np.allclose(cdf[: len(whole) - first], whole[first:], rtol=0, atol=1e-12)
    first, cdf = sm.poisson_window(4e8)
    mean = first + np.sum(1 - cdf)
    assert cdf[0] < 1e-18 and cdf[-1] == 1.0 and abs(mean - 4e8) < 1e-2


def test_same_rows_by_every_way(docs, monkeypatch):
    rows = lambda **kw: sorted((r.doc_id, r.copies, r.copy, round(r.rate, 9)) for r in sm.mix(docs, **kw).select("doc_id", "copies", "copy", "rate").collect())
    weights = {"s1": 0.5, None: 0.0001, "own": 0.0002, "not there": 1.0}
    want = rows(), rows(weights=weights)
    monkeypatch.setattr(sm, "CHUNK", 7)
    assert (rows(), rows(weights=weights)) == want
    monkeypatch.setattr(sm, "ENTRIES", 0)  # Python draws row by row
    assert (rows(), rows(weights=weights)) == want
    monkeypatch.setattr(sm, "SOURCES", 3)  # and the rates are a joined table
    assert (rows(), rows(weights=weights)) == want
