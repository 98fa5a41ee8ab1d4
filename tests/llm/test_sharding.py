import zlib
from collections import Counter

import numpy as np
import pytest
from llm_helpers import SF, table

from finegrain.llm import sharding as sh


@pytest.mark.parametrize("n", [1, 2, 3, 5, 16, 17, 1000, 4097])
def test_permutation(n):
    out = sh.permute(np.arange(n), n)
    assert sorted(out.tolist()) == list(range(n))
    assert n < 16 or out.tolist() != list(range(n))
    assert (sh.permute(np.arange(n), n) == out).all() and (n < 16 or (sh.permute(np.arange(n), n, seed=5) != out).any())


def walk(x, n, seed=sh.SEED):
    """The network by its definition, one number at a time."""
    bits = sh.half_bits(n)
    mask = (1 << bits) - 1
    while True:
        left, right = x >> bits, x & mask
        for key in sh.round_keys(seed):
            m = ((right ^ (key & mask)) * sh.MULTIPLY + key) % 2**31
            left, right = right, left ^ (((m >> 9) ^ m) & mask)
        x = left << bits | right
        if x < n:
            return x


def test_shards_by_hand(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = sh.shard(docs.repartition(6), 16).collect()
    n = docs.count()
    ordered = sorted(docs.collect(), key=lambda r: r.doc_id)
    want = {}
    for at, r in enumerate(ordered):
        p = walk(at, n)
        raw = (r.text or "").encode()
        want[r.doc_id] = (len(raw) + 1, zlib.crc32(raw), p % 16, p // 16)
    assert {r.doc_id: (r["size"], r.text_crc32, r.shard, r.slot) for r in rows} == want
    counts = Counter(r.shard for r in rows)
    assert max(counts.values()) - min(counts.values()) <= 1


def test_edges(spark, tmp_path):
    rows = [(None, None), (None, None), (1, ""), (1, ""), (1, "x"), (2, "é" * 1000)]
    docs = table(spark, [(*r, 5, 6) for r in rows], "doc_id long, text string, shard long, slot long")
    out = sh.shard(docs, 4).collect()
    assert len(out) == 6 and sorted(r["size"] for r in out) == [1, 1, 1, 1, 2, 2001]
    slots = {}
    for r in out:
        slots.setdefault(r.shard, []).append(r.slot)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert sh.shard(table(spark, [], "doc_id long, text string")).collect() == []
    sh.write_shards(docs, str(tmp_path / "out"), 4)
    assert spark.read.parquet(str(tmp_path / "out")).count() == 6
