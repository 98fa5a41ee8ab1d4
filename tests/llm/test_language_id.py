import math
import subprocess
import sys
import zlib
from collections import Counter
from pathlib import Path

import numpy as np
import pytest
from llm_helpers import SF, table

from finegrain.llm import language_id as li


@pytest.mark.parametrize("n", [1, 2, 3, 4, 7, 8, 40])
def test_codewords_are_apart(n):
    code = li.codewords(n)
    assert code.shape[0] == n and set(np.unique(code)) <= {-1.0, 1.0}
    if n > 1:
        distance = (code.shape[1] - code @ code.T) / 2 + np.diag([np.inf] * n)
        assert distance.min() >= max(1, code.shape[1] // 4)
        assert (np.abs(code.sum(0)) < n).all()


def test_held_out_accuracy(spark):
    docs = spark.read.parquet(f"{SF.replace('0.001', '0.01')}/documents.parquet")
    model = li.train(docs.where(~li.held_out()))
    rows = li.predict(docs, model).join(docs.select("doc_id", "lang").withColumn("held", li.held_out()), "doc_id").collect()
    held = [r for r in rows if r.held]
    assert sum(r.lang == r.lang_pred for r in held) / len(held) > 0.97
    assert all(0 <= r.score <= 1 and r.ambiguous == (r.score < li.AMBIGUOUS) for r in rows)


def test_labels_and_neighbours_are_no_input(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    model = li.train(docs)
    one = {r.doc_id: (r.lang_pred, round(r.score, 5)) for r in li.predict(docs, model).collect()}
    two = {r.doc_id: (r.lang_pred, round(r.score, 5)) for r in li.predict(docs.selectExpr("doc_id", "text", "'xx' AS lang").repartition(7), model).collect()}
    assert one == two


def test_edges(spark):
    words = {"en": "the cat and the dog", "fr": "le chat et la souris"}
    rows = [(i, words[x] * (1 + i % 3), x, 1.0) for i, x in enumerate(["en", "fr"] * 10)]
    rows += [(100, None, "en", 1.0), (101, "the cat", None, 1.0), (102, "12 !!", "fr", 1.0), (103, "", "fr", 1.0), (None, "et la souris " * 5000, "fr", 1.0), (104, "日本", "en", 1.0), (101, "the cat", None, 1.0)]
    docs = table(spark, rows, "doc_id long, text string, lang string, score double")
    out = {r.doc_id: r for r in li.predict(docs, li.train(docs)).collect()}
    assert [out[i].lang_pred for i in (100, 101, 102, 103, None)] == ["und", "en", "und", "und", "fr"]
    assert out[100].score == 0 and out[104].lang_pred in words
    assert li.predict(docs.limit(0), li.train(docs)).collect() == []
    nothing = li.train(docs.where("lang IS NULL"))
    assert {r.lang_pred for r in li.predict(docs, nothing).collect()} == {"und"}
    alone = li.train(docs.where("lang = 'en'"))
    assert {r.lang_pred for r in li.predict(docs, alone).collect()} == {"en", "und"}


def plain_grams(text):
    """Numbers of a text's 2-grams and 3-grams (the latter DIMENSIONS higher), one by one."""
    raw = (" " + text.lower() + "   ").encode()
    raw = bytes(((c | 32) if 65 <= c <= 90 or 97 <= c <= 122 else 32) if c < 128 else c for c in raw) + b"  "
    out = []
    for a, b, c in zip(raw, raw[1:], raw[2:]):
        two = a * 256 + b
        out += [two, li.DIMENSIONS + ((two * 0x9E3779B1 + c * 0x85EBCA6B) % 2**32 >> 16)]
    return out


def test_all_rows_against_plain_python(spark):
    """Counts, classifiers, bit weights, margins, losses and the choice, in loops over single numbers."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = [tuple(r) for r in docs.select("doc_id", "text", "lang").collect()]
    learn = [(t, x) for i, t, x in rows if zlib.crc32(str(i).encode()) % 5 and t is not None and x is not None]
    names = sorted({x for _, x in learn})
    code = li.codewords(len(names)).tolist()
    bits, size = range(len(code[0])), 2 * li.DIMENSIONS
    counts = {x: Counter() for x in names}
    for t, x in learn:
        counts[x].update(plain_grams(t))
    whole = {x: sum(c.values()) + 0.5 * size for x, c in counts.items()}
    weights = {}

    def weight(g, b):
        if (g, b) not in weights:
            sides = {1.0: [], -1.0: []}
            for x, word in zip(names, code):
                sides[word[b]].append((counts[x][g] + 0.5) / whole[x])
            weights[g, b] = math.log(sum(sides[1.0]) / len(sides[1.0])) - math.log(sum(sides[-1.0]) / len(sides[-1.0]))
        return weights[g, b]

    def margins(text):
        seen = Counter(plain_grams(text))
        n = sum(seen.values())
        return [sum(k * weight(g, b) for g, k in seen.items()) / n * min(n, li.EVIDENCE) for b in bits]

    right, n = {x: [0] * len(bits) for x in names}, Counter()
    for t, x in learn:
        n[x] += 1
        for b, m in enumerate(margins(t)):
            right[x][b] += m * code[names.index(x)][b] > 0
    trust = {x: [(r + 1) / (n[x] + 2) for r in right[x]] for x in names}

    got = {r.doc_id: r for r in li.predict(docs, li.train(docs.where(~li.held_out()))).collect()}
    assert len(got) == len(rows)
    for i, t, _ in rows:
        if t is None or not any(map(str.isalpha, t)):
            assert (got[i].lang_pred, got[i].score) == ("und", 0)
            continue
        ms = margins(t)
        losses = [len(bits) * sum(w / sum(trust[x]) * math.log1p(math.exp(-m * c)) for w, m, c in zip(trust[x], ms, word)) for x, word in zip(names, code)]
        best = min(losses)
        assert got[i].lang_pred == names[losses.index(best)]
        assert abs(got[i].score - 1 / sum(math.exp(best - x) for x in losses)) < 1e-4


def test_sample_of_any_number_of_rows():
    for known in (1, 20_000, 10**6, 3 * 10**10, 10**14):
        chosen = li.share_of(li.TRAIN_ROWS, known) / 2**63 * known
        assert chosen == pytest.approx(min(known, li.TRAIN_ROWS), rel=0.01)


def test_sample_of_a_few_rows(spark):
    docs = spark.range(100_000).selectExpr("id AS doc_id", "'a b c' AS text", "'en' AS lang")
    assert 300 < li.labelled(docs, rows=500).count() < 700
    assert li.labelled(docs, rows=10**9).count() == 100_000


def test_many_labels(spark):
    rng = np.random.default_rng(3)
    words = ["".join(chr(97 + c) for c in rng.integers(0, 26, 60)) for _ in range(1200)]
    rows = [(i, " ".join([words[x]] * 5), f"l{x:04}") for i, x in enumerate(list(range(1200)) * 2)]
    docs = table(spark, rows, "doc_id long, text string, lang string")
    model = li.train(docs, rows=10**6)
    assert len(model.languages) == 1200
    got = {r.doc_id: r.lang_pred for r in li.predict(docs, model).collect()}
    assert sum(got[i] == x for i, _, x in rows) > 0.95 * len(rows)
    assert len(np.unique(li.codewords(3000), axis=0)) == 3000


def test_a_text_of_20_mb_in_bounded_memory():
    code = """
import resource, sys
import numpy as np
sys.path.insert(0, sys.argv[1])
from finegrain.llm import language_id as li
code = li.codewords(7)
model = li.Model(list("abcdefg"), code, np.random.default_rng(1).normal(size=(2 * li.DIMENSIONS, code.shape[1])).astype(np.float32), np.full(code.shape, 1 / code.shape[1]))
text = "une phrase assez courte, " * 800_000
names, score = model.predict([text, "abc"], li.letters_only())
short = li.Model.predict(model, [text[:2_000_000]], li.letters_only())
assert names[0] == short[0][0] and len(names) == 2
assert resource.getrusage(resource.RUSAGE_SELF).ru_maxrss < 1_000_000, resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
"""
    subprocess.run([sys.executable, "-c", code, str(Path(__file__).parents[2])], check=True, timeout=300)
