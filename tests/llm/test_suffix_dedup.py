import hashlib
import random

import numpy as np
from llm_helpers import SF, table

from finegrain.llm import suffix_dedup as sd
from finegrain.llm.packed import Chunk


def brute(rows, length=sd.LENGTH):
    """doc_id -> (bytes, removed, spans, digest), straight from the definition."""
    first = {}
    for i, t in rows:
        raw = (t or "").encode()
        for p in range(len(raw) - length + 1):
            w = raw[p : p + length]
            if i is not None and i < first.get(w, float("inf")):
                first[w] = i
    out = []
    for i, t in rows:
        raw = (t or "").encode()
        gone = np.zeros(len(raw) + 1, bool)
        for p in range(len(raw) - length + 1):
            if first.get(raw[p : p + length], float("inf")) < (float("inf") if i is None else i):
                gone[p : p + length] = True
        kept = bytes(b for b, g in zip(raw, gone) if not g)
        spans = int((np.diff(np.append(False, gone).astype(int)) == 1).sum())
        out.append((i, len(raw), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=repr)


def ours(df):
    return sorted(((r.doc_id, r.n_bytes, sum(s.end - s.start for s in r.spans), len(r.spans), r.kept_sha256) for r in sd.cut_repeats(df).collect()), key=repr)


def test_given_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    assert ours(docs.repartition(5)) == brute([tuple(r) for r in docs.collect()])


def hard_rows():
    rng = random.Random(3)
    passage = "".join(rng.choice("abc \n") for _ in range(180))
    periodic, zeros = "xy" * 400, "\0" * 130
    rows = [(None, passage), (None, None), (5, ""), (5, "short"), (7, periodic), (3, periodic[1:500]), (9, zeros), (8, "a" + zeros[:70] + "b"), (4, "é" * 60), (2, "ü" + "é" * 40)]
    rows += [(100 + i, "".join(rng.choice("abcdefgh ") for _ in range(rng.randint(0, 90))) + passage[rng.randint(0, 60) :] + str(i) * rng.randint(0, 9)) for i in range(60)]
    return rows + [(100, passage), (100, passage), (7, periodic)]


def test_hard_rows(spark, monkeypatch):
    rows = hard_rows()
    want = brute(rows)
    assert ours(table(spark, rows, "doc_id long, text string").repartition(7)) == want
    monkeypatch.setattr(sd, "HOT_PIECES", 3)  # deal most anchors by their windows
    assert ours(table(spark, rows, "doc_id long, text string").repartition(7)) == want


def test_empty_table_and_clashing_columns(spark):
    assert ours(table(spark, [], "doc_id long, text string")) == []
    df = table(spark, [(1, "x" * 60, 3, 4), (2, "x" * 60, 3, 4)], "doc_id long, text string, g long, body long")
    assert [r[2] for r in ours(df)] == [0, 60]


def test_suffixes_are_sorted():
    rng = random.Random(5)
    pieces = [bytes(rng.choice(b"ab\0\xff") for _ in range(rng.randint(1, 70))) for _ in range(50)]
    raw = b"".join(p + b"\0" for p in pieces)
    ends = np.cumsum([len(p) + 1 for p in pieces]) - 1
    order = sd.sorted_suffixes(raw, ends)
    assert sorted(order.tolist()) == list(range(len(raw)))
    end = {p: int(ends[np.searchsorted(ends, p)]) for p in range(len(raw))}
    keys = [raw[p : min(end[p], p + sd.LENGTH)] for p in order.tolist()]
    padded = [k.ljust(sd.LENGTH, b"\0") for k in keys]
    assert padded == sorted(padded)


def test_pieces_cover_all_windows_once(monkeypatch):
    monkeypatch.setattr(sd, "BLOCK", 97)
    texts = [b"q" * 300, b"", b"abc", bytes(range(256)) * 2, b"z" * 50]
    chunk = Chunk(0, np.arange(5), np.ones(5, bool), np.zeros(5), np.cumsum([0, *map(len, texts)]), b"".join(texts))
    start, count, _, doc = sd.pieces_of(chunk)
    seen = sorted(int(s) + i for s, n in zip(start, count) for i in range(n))
    assert seen == [chunk.starts[d] + i for d, t in enumerate(texts) for i in range(len(t) - sd.LENGTH + 1)]
    assert all(chunk.starts[d] <= s for s, d in zip(start, doc))
