import re

import pytest
from llm_helpers import table

from finegrain.llm import quality_rules as qr


def brute(text):
    """The five measures, from their definitions."""
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    windows = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    hit = {i + k for i, w in enumerate(windows) if windows.count(w) > 1 for k in range(5)}
    return len(words), sum(map(len, words)), sum(text.count(c) for c in "#*$%&|<>"), sum(x in lines[:i] for i, x in enumerate(lines)), len(hit)


def brute_kept(text):
    n, chars, symbols, dup, again = brute(text)
    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    upper, lower = len(re.findall("[A-Z]", text or "")), len(re.findall("[a-z]", text or ""))
    stutters = sum(a == b for a, b in zip(words, words[1:]))
    return not (n < 10 or 100 * again > 20 * n or 10 * symbols > n or chars < 2 * n or chars > 25 * n or 2 * dup > len(lines) or 4 * stutters > n or upper > lower)


TEXTS = [
    None, "", " \n\t ", "a b c d e f g h i j", "é à ü " * 8, "one two three four five six\n" * 3 + "tail of words that differ from all of those",
    "x " * 3000, "a\x1fb c\x0bd\x1ce f", "### $$$ word " * 20, "THE SHOUTING OF MANY WORDS THAT ALL ARE CAPITALS HERE", "\n".join(["same line here"] * 9), "w" * 100_000,
    "日本 語 の " * 5 + "end", "line one is fine and long\n\nline two is fine too and longer\n line one is fine and long",
]


def test_measures_and_verdicts(spark):
    got = {r.doc_id: r for r in qr.measured(table(spark, [(i, t) for i, t in enumerate(TEXTS)], "doc_id long, text string")).collect()}
    for i, t in enumerate(TEXTS):
        n, chars, symbols, dup, again = brute(t)
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (n, chars, symbols, dup, again), t
        assert r.base_failed == (n < 10 or 100 * again > 20 * n) and r.kept == brute_kept(t), t


@pytest.mark.parametrize("order", [None, [*qr.RULES, *qr.BASE_RULES], [*qr.BASE_RULES, *reversed(qr.RULES)]])
def test_order_never_changes_verdicts(spark, order):
    docs = table(spark, [(i, t, None, None) for i, t in enumerate(TEXTS * 2)], "doc_id long, text string, n_words long, kept string")
    kept = qr.keep_good(docs, order)
    assert kept.columns == docs.columns
    assert sorted(r.doc_id for r in kept.collect()) == [i for i, t in enumerate(TEXTS * 2) if brute_kept(t)]


def test_cascade_prefers_rejections_per_second():
    assert qr.cascade_order({"slow": (0.9, 1.0), "fast": (0.3, 0.01), "idle": (0.0, 0.001)}) == ["fast", "slow", "idle"]


def test_empty(spark):
    assert qr.measured(table(spark, [], "doc_id long, text string")).collect() == []
