import hashlib
import re

from llm_helpers import SF, table

from finegrain.llm import decontamination as dc

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(text):
    return WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))


def brute(rows, items, size=13):
    patterns = {}
    for i, t in items:
        w = words(t)
        n = min(size, len(w))
        for k in range(len(w) - n + 1) if n else ():
            patterns.setdefault(tuple(w[k : k + n]), set()).update([] if i is None else [str(i)])
    out = []
    for i, t in rows:
        w, hit, ids = words(t), set(), set()
        for n in {len(p) for p in patterns}:
            for k in range(len(w) - n + 1):
                if (found := patterns.get(tuple(w[k : k + n]))) is not None:
                    hit |= set(range(k, k + n))
                    ids |= found
        out.append((i, len(w), len(hit), len(ids), hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return sorted(out, key=repr)


def ours(docs, items, **more):
    return sorted(((r.doc_id, r.n_words, r.n_hit, len(r["items"]), dc.items_digest(r["items"]), r.contaminated) for r in dc.find(docs, items, **more).collect()), key=repr)


LONG = " ".join(f"w{i}" for i in range(30))
ITEMS = [(1, LONG), (2, "Short item, of five WORDS"), (3, None), (4, " .,"), (None, "nobody's item"), (10, LONG), (5, "é è"), (6, "short item of five words and then w3")]
ROWS = [
    (1, f"before {LONG.upper()} after"), (2, "a short, item of\nfive words!"), (3, None), (4, ""), (None, "nobody s item"), (6, "x é-è y"), (6, "x é-è y"),
    (7, " ".join(f"w{i}" for i in range(12))), (8, " ".join(f"w{i}" for i in range(13))), (9, "filler " * 2000 + "short item of five words"), (10, "short item of five wordsx"),
]


def test_hard_rows_one_block_and_many(spark):
    docs, items = table(spark, ROWS, "doc_id long, text string"), table(spark, ITEMS, "item_id long, text string")
    assert ours(docs, items) == brute(ROWS, ITEMS)
    assert ours(docs, items, most=60) == brute(ROWS, ITEMS)
    clean = [(r.doc_id, r.text) for r in dc.keep_clean(docs.withColumn("n_hit", docs.doc_id), items).collect()]
    bad = {r[0] for r in brute(ROWS, ITEMS) if r[5]}
    assert sorted(clean, key=repr) == sorted(((i, t) for i, t in ROWS if i not in bad), key=repr)


def test_spans_lead_back_to_the_original(spark):
    text = "Ünder the – short,  ITEM of\nfive wOrds, and more"
    row = dc.find(table(spark, [(1, text)], "doc_id long, text string"), table(spark, ITEMS, "item_id long, text string")).first()
    assert [text.encode()[s.start : s.end].decode() for s in row.spans] == ["short,  ITEM of\nfive wOrds"]


def test_empty_benchmark_and_empty_table(spark):
    docs, none = table(spark, ROWS, "doc_id long, text string"), table(spark, [], "item_id long, text string")
    assert ours(docs, none) == brute(ROWS, [])
    assert ours(docs.limit(0), table(spark, ITEMS, "item_id long, text string")) == []


def test_given_documents(spark):
    docs, items = (spark.read.parquet(f"{SF}/{t}.parquet").select(k, "text") for t, k in (("documents", "doc_id"), ("benchmark", "item_id")))
    assert ours(docs, items) == brute([tuple(r) for r in docs.collect()], [tuple(r) for r in items.collect()])


def test_more_words_than_characters(spark, monkeypatch):
    """Words of two characters each: only whole words match."""
    import numpy as np

    rng = np.random.default_rng(1)
    items = [(i, " ".join(f"w{x}" for x in rng.integers(0, 6, 15))) for i in range(8)] + [(9, "w1 w2"), (10, "w3")]
    rows = [(i, " ".join(f"w{x}" for x in rng.integers(0, 6, 60)) + (" " + items[i % 8][1]) * (i % 2)) for i in range(30)]
    monkeypatch.setattr(dc, "CODES", 3)
    block = next(dc.pattern_blocks(table(spark, items, "item_id long, text string")))
    scanner = dc.Scanner(block)
    assert scanner.width == 2
    for (i, t), want in zip(rows, sorted(brute(rows, items), key=lambda r: r[0])):
        n, ranges, ids = scanner.scan(t)
        assert (i, n, sum(b - a for a, b in dc.joined(ranges)), len(ids)) == want[:4]
    assert len({dc.code_point(n) for n in range(0xD700, 0xE900)}) == 0x1200 and not any(0xD800 <= ord(dc.code_point(n)) < 0xE000 for n in range(0xD000, 0xE900))
