import random

import pytest
from llm_helpers import SF, table

from finegrain.llm import line_dedup as ld

BLANK = " \t\r\x0b\x0c"


def brute(rows, min_sites):
    sites = {}
    for _, text, site in rows:
        for line in (text or "").split("\n"):
            if line.strip(BLANK) and site is not None:
                sites.setdefault(line.strip(BLANK), set()).add(site)
    bad = {x for x, s in sites.items() if len(s) >= min_sites}
    out = []
    for i, text, _ in rows:
        lines = (text or "").split("\n")
        out.append((i, sum(bool(x.strip(BLANK)) for x in lines), sum(x.strip(BLANK) in bad for x in lines), "\n".join(x for x in lines if x.strip(BLANK) not in bad)))
    return sorted(out, key=repr)


def ours(df, min_sites):
    rows = ld.strip_boilerplate(df.select("doc_id", "text", "source"), min_sites=min_sites).collect()
    return sorted(((r.doc_id, r.n_lines, r.n_removed, r.kept_text) for r in rows), key=repr)


@pytest.mark.parametrize("min_sites", [2, 5, 12])
def test_given_documents(spark, min_sites):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "source")
    assert ours(docs, min_sites) == brute([tuple(r) for r in docs.collect()], min_sites)


def test_hard_rows(spark):
    rng = random.Random(2)
    rows = [(None, "footer", "a"), (1, None, "b"), (2, "", "c"), (3, "footer\n\nfooter  \n\tfooter\nown line", None), (4, "footer", "d"), (4, "footer", "d"), (5, " \n ", "e"), (6, "x" * 100_000 + "\nfooter", "f"), (7, "footer\r", "g")]
    rows += [(100 + i, "\n".join(f"line {rng.randint(0, 40)}" for _ in range(12)), f"s{rng.randint(0, 9)}") for i in range(200)]
    df = table(spark, rows, "doc_id long, text string, source string")
    for n in (2, 5, 10):
        assert ours(df, n) == brute(rows, n)


def test_near_threshold_lines_are_counted_exactly(spark):
    """Thousands of sites, estimates a few percent off: the verdicts are those of the exact counts."""
    rows = [(i, "\n".join(x for x, n in (("just below", 999), ("just there", 1000), ("far above", 3000)) if i < n), f"site{i}") for i in range(3000)]
    df = table(spark, rows, "doc_id long, text string, source string")
    assert ours(df, 1000) == brute(rows, 1000)


def test_native_plan_and_edges(spark):
    df = table(spark, [(1, "a\nb", "s", 7, "n")], "doc_id long, text string, source string, n_lines long, kept_text string")
    out = ld.strip_boilerplate(df)
    plan = out._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan
    assert sorted(out.columns) == sorted(df.columns + ["n_removed"])
    assert ours(table(spark, [], "doc_id long, text string, source string"), 2) == []
