import random
from collections import defaultdict

import numpy as np
import pytest
from llm_helpers import SF, table

from finegrain.llm import minhash_dedup as md


def sets_of(rows, k):
    out = []
    for i, t in rows:
        words = (t or "").encode().translate(md.lower_table()).split()
        n = min(k, len(words))
        out.append((i, {tuple(words[j : j + n]) for j in range(len(words) - n + 1)} if words else set()))
    return out


def brute(rows, k, alike=(80, 100)):
    """doc_id -> (set size, component, kept) over all pairs that share a shingle."""
    sets = sets_of(rows, k)
    top = {i: i for i, _ in sets}

    def find(x):
        while top[x] != x:
            x = top[x]
        return x

    index = defaultdict(list)
    for n, (_, s) in enumerate(sets):
        for x in s:
            index[x].append(n)
    for n, (i, s) in enumerate(sets):
        common = defaultdict(int)
        for x in s:
            for m in index[x]:
                if m < n:
                    common[m] += 1
        for m, c in common.items():
            if alike[1] * c >= alike[0] * (len(s) + len(sets[m][1]) - c):
                a, b = find(i), find(sets[m][0])
                top[max(a, b)] = min(a, b)
    return {(i, len(s), find(i), find(i) == i) for i, s in sets}


def ours(df, k):
    return {(r.doc_id, r.n_shingles, r.component_id, r.kept) for r in md.near_duplicates(df, k).collect()}


@pytest.mark.parametrize("k", [4, 5])
def test_given_documents(spark, k):
    docs = spark.read.parquet(f"{SF.replace('0.001', '0.01')}/documents.parquet").select("doc_id", "text")
    assert ours(docs, k) == brute([tuple(r) for r in docs.collect()], k)


def test_chains_ties_and_blocks(spark, monkeypatch):
    """Chains whose ends aren't alike, templates just below and at the threshold, one large group."""
    rng = random.Random(7)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(5))
    rows, n = [], 0
    for _ in range(12):
        text = [word() for _ in range(120)]
        for _ in range(8):  # each step changes a few words of the one before
            rows.append((n := n + 1, " ".join(text)))
            text = list(text)
            for _ in range(rng.randint(1, 4)):
                text[rng.randrange(120)] = word()
    base = [word() for _ in range(150)]
    for _ in range(120):
        text = list(base)
        for _ in range(rng.randint(0, 8)):
            text[rng.randrange(150)] = word()
        rows.append((n := n + 1, " ".join(text)))
    rng.shuffle(rows)
    monkeypatch.setattr(md, "BLOCK", 16)
    monkeypatch.setattr(md, "SET_BLOCK", 8)
    for _ in range(60):  # copies that are mostly just below the threshold
        text = list(base)
        for _ in range(rng.randint(4, 12)):
            text[rng.randrange(150)] = word()
        rows.append((n := n + 1, " ".join(text)))
    assert ours(table(spark, rows, "doc_id long, text string"), 4) == brute(rows, 4)


def test_edges(spark):
    same = "one two three four five six seven"
    rows = [(1, None), (2, ""), (3, " \n\t"), (4, "One"), (5, "one"), (6, same), (7, same.upper()), (8, "É a b c d"), (9, "é a b c d"), (None, same), (None, "alone here"), (6, same)]
    got = sorted(((r.doc_id, r.n_shingles, r.component_id, r.kept) for r in md.near_duplicates(table(spark, rows, "doc_id long, text string"), 4).collect()), key=repr)
    want = [(1, 0, 1, True), (2, 0, 2, True), (3, 0, 3, True), (4, 1, 4, True), (5, 1, 4, False), (6, 4, 6, True), (6, 4, 6, True), (7, 4, 6, False), (8, 2, 8, True), (9, 2, 9, True), (None, 1, None, True), (None, 4, 6, False)]
    assert got == sorted(want, key=repr)
    kept = md.keep_one_of_each(table(spark, [(*r, "x") for r in rows], "doc_id long, text string, id string")).collect()
    assert sorted((r.doc_id for r in kept), key=str) == sorted([1, 2, 3, 4, 6, 8, 9, None], key=str)
    assert md.near_duplicates(table(spark, [], "doc_id long, text string"), 4).collect() == []


def test_estimate_is_unbiased():
    rng = np.random.default_rng(1)
    for j in (0.3, 0.8):
        n = 3000
        x = rng.integers(0, 2**63, 2 * n, np.uint64)
        common = int(2 * n * j / (1 + j))
        a, b = x[:n], np.concatenate([x[:common], x[n : 2 * n - common]])
        true = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
        mins = md.minima([np.unique(a), np.unique(b)], md.BANDS * md.ROWS)
        s = md.packed_signature(mins)
        assert abs(float(md.estimate(s[0], s[1])) - true) < 0.16


def test_components_of_hubs_and_paths(spark, monkeypatch):
    links = [(0, i) for i in range(5, 400)] + [(i, i + 1) for i in range(1000, 1060)] + [(2000, 2000), (1030, 30)]
    df = spark.createDataFrame(links, "a long, b long")
    want = {i: 0 for i in [0, *range(5, 400), *range(1000, 1061)]}
    for most in (md.HUB_ROWS, 0):
        monkeypatch.setattr(md, "HUB_ROWS", most)
        assert {r.id: r.component for r in md.components(df).collect()} == want


def test_few_meetings_are_worth_another_try(spark, monkeypatch):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    monkeypatch.setattr(md, "MEETINGS", 0)
    assert ours(docs, 4) == brute([tuple(r) for r in docs.collect()], 4)
