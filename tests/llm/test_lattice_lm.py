import math
import zlib
from collections import Counter

import numpy as np
import pytest
from llm_helpers import SF, table

from finegrain.llm import lattice_lm as lm
from finegrain.llm.queries import tokenizer_path

PATH = tokenizer_path("piece_bpe_32k.model")


def every_way(text, log_p):
    """Log of the sum over all segmentations, by enumeration."""
    if not text:
        return [0.0]
    return [log_p[text[:n]] + rest for n in range(1, len(text) + 1) if text[:n] in log_p for rest in every_way(text[n:], log_p)]


def test_forward_sums_all_segmentations():
    pieces = [b" ", b"a", b"b", b" a", b"ab", b" ab", b"ba", b"bab"]
    log_p = {p: -0.3 * i - 1 for i, p in enumerate(pieces)}
    lattice = lm.Lattice(pieces, np.array([log_p[p] for p in pieces]))
    words = [b"a", b"ab", b"abab", b"babab", b"bbbb", b"ba"]
    want = [np.logaddexp.reduce(every_way(b" " + w, log_p)) for w in words]
    assert np.allclose(lm.word_log_p(lattice, words), want)


def test_expected_uses_are_the_gradient():
    rng = np.random.default_rng(2)
    pieces = [b" ", b"a", b"b", b" a", b"ab", b"aba"]
    log_p = -rng.random(len(pieces)) - 1
    words, times = [b"abab", b"a", b"baab"], [3.0, 5.0, 2.0]
    total = lambda x: sum(t * v for t, v in zip(times, lm.word_log_p(lm.Lattice(pieces, x), words)))
    uses = np.zeros(len(pieces))
    for own, text in lm.by_length(words):
        uses += lm.Lattice(pieces, log_p).uses(text, np.array(times)[own])
    step = 1e-6
    slope = [(total(log_p + step * e) - total(log_p - step * e)) / (2 * step) for e in np.eye(len(pieces))]
    assert np.allclose(uses, slope, atol=1e-5)


def expected_base(rows):
    held = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 7 == 2
    split = [(i, (t or "").encode().translate(lm.lower_table()).split()) for i, t in rows]
    count = Counter(w for i, ws in split if not held(i) for w in ws)
    ends = sum(not held(i) for i, _ in split)
    n, v = sum(count.values()) + ends, len(count) + (ends > 0)
    out = []
    for i, ws in split:
        base = sum(math.log10((count[w] + 1) / (n + v + 1)) for w in ws) + math.log10((ends + 1) / (n + v + 1))
        out.append((i, held(i), len(ws) + 1, sum(count[w] > 0 for w in ws) + (ends > 0), n, round(base, 6)))
    return sorted(out, key=repr)


def ours(df):
    rows = lm.scores(df, PATH, rounds=1).collect()
    assert all(math.isfinite(r.score) and r.score < 0 for r in rows)
    return sorted(((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in rows), key=repr)


def test_base_scores_of_given_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    assert ours(docs.repartition(3)) == expected_base([tuple(r) for r in docs.collect()])


def test_edges(spark):
    rows = [(1, None), (2, ""), (None, "A b"), (3, "日本 " + "x" * 3000 + " \0 b"), (3, "b"), (4, "b\x1fb B")]
    assert ours(table(spark, rows, "doc_id long, text string")) == expected_base(rows)
    assert ours(table(spark, [], "doc_id long, text string")) == []


def test_rounds_raise_held_out_likelihood(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    score = [sum(r.score for r in lm.scores(docs, PATH, rounds=n).where("held_out").collect()) for n in (0, 1, 2, lm.ROUNDS)]
    assert score[0] < score[1] < score[2]
    assert abs(score[3] - score[2]) < 0.01 * abs(score[2])  # more rounds gain less than a hundredth


def test_known_documents_are_scored_like_words(spark):
    """Where training has seen every word, the score is that of a smoothed model of words: within a few percent of the add-one base."""
    rows = [r for r in lm.scores(spark.read.parquet(f"{SF}/documents.parquet"), PATH).collect() if r.n_known == r.n_tokens and r.n_tokens > 20]
    assert len(rows) > 50 and abs(sum(r.score for r in rows) / sum(r.base_score for r in rows) - 1) < 0.05


@pytest.mark.parametrize("rounds", [0, 2])
def test_weights_are_a_distribution(rounds, spark):
    docs = table(spark, [(i, "some words and more words") for i in range(20)], "doc_id long, text string")
    chunks = lm.pack(docs, lm.HELD_OUT)
    words = lm.merged_words(lm.questions(chunks, lm.ask_words(8)))
    model = lm.fit(words, 20, PATH, rounds)
    assert abs(np.exp(model.log_p).sum() + math.exp(model.end) - 1) < 1e-6


def plain_forward(word, log_p, longest):
    """alpha of b" " + word, piece by piece."""
    text = b" " + word
    alpha = [0.0] + [-math.inf] * len(text)
    for j in range(1, len(text) + 1):
        ways = [alpha[i] + log_p[text[i:j]] for i in range(max(0, j - longest), j) if text[i:j] in log_p]
        alpha[j] = max(ways) + math.log(sum(math.exp(w - max(ways)) for w in ways)) if ways and max(ways) > -math.inf else -math.inf
    return alpha


def plain_scores(rows, rounds):
    """Every row's score: expectation maximisation, whole-word arcs and sums in dictionaries and loops."""
    held = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 7 == 2
    split = [(i, (t or "").encode().translate(lm.lower_table()).split()) for i, t in rows]
    count = Counter(w for i, ws in split if not held(i) for w in ws)
    ends = sum(not held(i) for i, _ in split)
    start = lm.vocabulary(PATH)
    longest = max(map(len, start))
    log_p, end = {p: x + math.log(0.99) for p, x in start.items()}, math.log(0.01)
    for _ in range(rounds if ends else 0):
        uses = Counter()
        for w in count:
            text, alpha = b" " + w, plain_forward(w, log_p, longest)
            beta = [-math.inf] * len(text) + [0.0]
            for i in range(len(text) - 1, -1, -1):
                ways = [(text[i:j], log_p[text[i:j]] + beta[j]) for j in range(i + 1, min(len(text), i + longest) + 1) if text[i:j] in log_p]
                for p, x in ways:
                    uses[p] += math.exp(alpha[i] + x - alpha[-1])
                beta[i] = max(x for _, x in ways) + math.log(sum(math.exp(x - max(y for _, y in ways)) for _, x in ways)) if ways else -math.inf
        whole = math.log(sum(uses.values()) + 1 + lm.SMOOTH * (len(start) + 1))
        log_p, end = {p: math.log(uses[p] + lm.SMOOTH) - whole for p in start}, math.log(1 + lm.SMOOTH) - whole
    once, twice = (sum(c == k for c in count.values()) + (ends == k) for k in (1, 2))
    total, distinct = sum(count.values()) + ends, len(count) + (ends > 0)
    cut = min(0.9, max(0.1, once / (once + 2 * twice))) if once + twice else 0.5
    rest = cut * distinct / total if total else 1.0
    begins = math.exp(end) + sum(math.exp(x) for p, x in log_p.items() if p[:1] == b" ")
    token = lambda c, x: math.log((c - cut) / total + rest * x if c else rest * x) / math.log(10)
    score = {w: token(count[w], math.exp(plain_forward(w, log_p, longest)[-1])) for w in {w for _, ws in split for w in ws}}
    return [(i, sum(score[w] for w in ws) + token(ends, math.exp(end) / begins)) for i, ws in split]


@pytest.mark.parametrize("each", [20_000, lm.PART_BYTES])
def test_all_scores_against_plain_python(spark, each):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    want = dict(plain_scores([tuple(r) for r in docs.collect()], 2))
    got = {r.doc_id: r.score for r in lm.scores(docs.repartition(5), PATH, rounds=2, each=each).collect()}
    assert got.keys() == want.keys()
    assert all(abs(got[i] - want[i]) < 1e-6 * abs(want[i]) for i in want)


def test_edge_scores_against_plain_python(spark):
    rows = [(1, None), (2, ""), (None, "A b"), (3, "日本 b"), (4, "b\x1fb B"), (5, "x" * 40 + " c")]
    got = sorted(round(r.score, 6) for r in lm.scores(table(spark, rows, "doc_id long, text string"), PATH, rounds=1).collect())
    assert got == sorted(round(x, 6) for _, x in plain_scores(rows, 1))


def test_long_words_one_by_one():
    start = lm.vocabulary(PATH)
    pieces = sorted(start)
    lattice = lm.Lattice(pieces, np.array([start[p] for p in pieces]))
    text = np.frombuffer((" " + "thequickbrown日本語ßx" * 40).encode(), np.uint8)
    assert np.allclose(lattice.forward(text.reshape(1, -1))[:, 0], lattice.forward_long(text))
    (uses, likelihood), (uses_long, long_) = lattice.expected(text.reshape(1, -1), np.array([3.0])), lattice.expected_long(text, 3.0)
    assert np.allclose(uses, uses_long) and abs(likelihood - long_) < 1e-6
    at_once, lm.ARCS_AT_ONCE = lm.ARCS_AT_ONCE, 100
    try:
        assert np.allclose(lattice.forward_long(text), lattice.forward(text.reshape(1, -1))[:, 0])
        assert np.allclose(lattice.expected_long(text, 3.0)[0], uses)
    finally:
        lm.ARCS_AT_ONCE = at_once


def test_a_word_of_a_megabyte(spark):
    rows = [(1, "ab" * 500_000), (2, "a b"), (3, "x " * 600_000)]
    got = {r.doc_id: r for r in lm.scores(table(spark, rows, "doc_id long, text string"), PATH, rounds=1).collect()}
    assert got[1].n_tokens == 2 and got[3].n_tokens == 600_001
    assert all(math.isfinite(r.score) for r in got.values())


def test_known_words_beat_pieces_alone(spark):
    """Words of the corpus are likelier with their arcs than by their pieces."""
    rows = [(i, "zyxxyq wvuuvw") for i in range(1, 50)]
    r = lm.scores(table(spark, rows, "doc_id long, text string"), PATH, rounds=3).first()
    assert r.score > r.base_score - 0.2
