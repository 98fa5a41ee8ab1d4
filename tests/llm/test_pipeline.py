import hashlib
import math
from collections import Counter, defaultdict

import corpus_pipeline
from llm_helpers import SF, table
from test_decontamination import brute as contamination
from test_minhash_dedup import brute as components
from test_quality_rules import brute_kept


def poisson_count(rate, u):
    term, total, k = math.exp(-rate), math.exp(-rate), 0
    while total <= u:
        k += 1
        term *= rate / k
        total += term
        if term == 0:
            break
    return k


def expected(docs, items):
    docs = [d for d in docs if brute_kept(d["text"])]
    kept = {i for i, _, _, k in components([(d["doc_id"], d["text"]) for d in docs], 5) if k}
    docs = [d for d in docs if d["doc_id"] in kept]
    bad = {r[0] for r in contamination([(d["doc_id"], d["text"]) for d in docs], items) if r[5]}
    docs = [d for d in docs if d["doc_id"] not in bad]
    size = defaultdict(int)
    for d in docs:
        size[d["source"]] += len(d["text"].encode())
    whole = sum(size.values())
    roots = sum(b**0.5 for b in size.values())
    out = Counter()
    for d in docs:
        b = size[d["source"]]
        rate = b**0.5 / roots * whole / b
        digest = hashlib.md5(f"mix-1|{d['doc_id']}|{hashlib.md5(d['text'].encode()).hexdigest()}".encode()).hexdigest()
        u = (int(digest[:13], 16) + 0.5) / 2**52
        if n := poisson_count(rate, u):
            out[d["doc_id"]] = n
    return out


def test_pipeline_against_brute_force(spark):
    docs = [r.asDict() for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    items = [tuple(r) for r in spark.read.parquet(f"{SF}/benchmark.parquet").select("item_id", "text").collect()]
    rows = corpus_pipeline.run(spark, SF).collect()
    assert Counter(r.doc_id for r in rows) == expected(docs, items)
    texts = {d["doc_id"]: d["text"] for d in docs}
    assert all(r.text == texts[r.doc_id] and r["size"] == len(r.text.encode()) + 1 for r in rows)
    slots = defaultdict(list)
    for r in rows:
        slots[r.shard].append(r.slot)
    assert max(map(len, slots.values())) - min(map(len, slots.values())) <= 1
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())


def test_stages_on_hard_rows(spark):
    """Nulls in every column, empty texts, repeated rows, an empty table, extra columns with clashing names."""
    good = "the quick brown fox jumps over the lazy dog and runs far away from here today"
    other = " ".join(f"word{i}" for i in range(40))
    rows = [(None, good, None, None, None, 1), (1, None, "en", "a", 0, 1), (2, "", "en", "a", 0, 1), (3, other, None, None, None, 1), (3, other, None, None, None, 1), (4, other + " more", "en", "b", 1, None), (5, good + " twice", "en", "b", 1, None)]
    schema = "doc_id long, text string, lang string, source string, n_chars long, {} long"
    for extra in ("shard", "rate", "key", "g", "kept", "copies"):
        for data in (rows, []):
            docs = table(spark, data, schema.format(extra))
            for name, stage in corpus_pipeline.STAGES:
                out = stage(spark, docs, SF)
                if name != "sharding":
                    assert out.columns == docs.columns
                assert out.count() <= 50 and (data or out.count() == 0)
    cleaned = corpus_pipeline.near_duplicates(spark, corpus_pipeline.quality(spark, table(spark, rows, schema.format("x")), SF), SF)
    assert sorted((r.doc_id for r in cleaned.collect()), key=str) == [3, 5, None]
