"""Texts of more than a megabyte, and columns with the names that operators use themselves."""

import hashlib
import random
import zlib

import numpy as np
import pytest
from llm_helpers import SF, table
from test_decontamination import brute as contamination
from test_line_dedup import brute as without_lines
from tokenizers import Tokenizer

import corpus_pipeline
from finegrain.llm import decontamination as dc
from finegrain.llm import language_id as li
from finegrain.llm import line_dedup as ld
from finegrain.llm import minhash_dedup as md
from finegrain.llm import quality_rules as qr
from finegrain.llm import sharding as sh
from finegrain.llm import source_mixing as sm
from finegrain.llm import suffix_dedup as sd
from finegrain.llm import token_counts as tc
from finegrain.llm.queries import tokenizer_path

rng = random.Random(5)
WORDS = ["".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randint(2, 9))) for _ in range(3000)]
PROSE = "\n".join(" ".join(rng.choice(WORDS) for _ in range(12)) for _ in range(18_000))
RUN = "".join(rng.choice("abcdefgh") for _ in range(1_200_000))
ROWS = [(1, PROSE, "en", "a"), (2, RUN, "en", "b"), (3, PROSE, "en", "c"), (4, "a short line\nof words", "fr", "a"), (5, None, None, None)]
SCHEMA = "doc_id long, text string, lang string, source string"


@pytest.fixture(scope="module")
def docs(spark):
    assert len(PROSE) > 1_000_000
    return table(spark, ROWS, SCHEMA).repartition(3)


def test_line_dedup(docs):
    got = {(r.doc_id, r.n_lines, r.n_removed, hashlib.md5(r.kept_text.encode()).digest()) for r in ld.strip_boilerplate(docs, min_sites=2).collect()}
    assert got == {(i, n, m, hashlib.md5(t.encode()).digest()) for i, n, m, t in without_lines([(i, t, s) for i, t, _, s in ROWS], 2)}


def test_token_counts(docs):
    library = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))
    got = {r.doc_id: r for r in tc.token_counts(docs, tokenizer_path("byte_bpe_50k.json")).collect()}
    for i, t, _, _ in ROWS:
        assert got[i].n_tokens == len(library.encode(t or "", add_special_tokens=False).ids)
    assert len(library.encode(RUN[: got[2].fit_chars], add_special_tokens=False).ids) <= 512 < len(library.encode(RUN[: got[2].fit_chars + 8], add_special_tokens=False).ids)


@pytest.mark.parametrize("text", [RUN[:4000], PROSE[:9000], "don't stop, we'll  go " * 300, "日本語 " * 900])
def test_budget_is_met_by_the_longest_prefix(text):
    library = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))
    counter = tc.PrefixCounter(tokenizer_path("byte_bpe_50k.json"))
    count = lambda p: len(library.encode(text[:p], add_special_tokens=False).ids)
    for budget in (1, 100, 512):
        found = counter.fit(text, budget)
        assert count(found) <= budget
        longer = [p for p in range(found + 1, min(found + 40, len(text)) + 1) if count(p) <= budget]
        assert not longer or all(text[p - 1] in " '" or text[p - 2] == "'" for p in longer)


def test_substring_dedup(docs):
    got = {r.doc_id: r for r in sd.cut_repeats(docs).collect()}
    assert got[3].spans[0].end == len(PROSE) and len(got[3].spans) == 1 and got[1].spans == [] and got[2].spans == []
    assert got[3].kept_sha256 == hashlib.sha256(b"").hexdigest() and got[2].kept_sha256 == hashlib.sha256(RUN.encode()).hexdigest()


def test_near_duplicates(docs):
    got = {r.doc_id: (r.component_id, r.kept) for r in md.near_duplicates(docs).collect()}
    assert got == {1: (1, True), 2: (2, True), 3: (1, False), 4: (4, True), 5: (5, True)}


def test_mixing(docs):
    out = sm.mix(docs, epochs=3.0).collect()
    texts = {i: t for i, t, _, _ in ROWS}
    assert {r.doc_id for r in out} <= set(texts) and len(out) > 3 and all(r.text == texts[r.doc_id] for r in out)


def test_language(docs):
    got = {r.doc_id: r.lang_pred for r in li.predict(docs, li.train(docs)).collect()}
    assert [got[i] for i in (1, 2, 5)] == ["en", "en", "und"]


def test_sharding(docs):
    got = {r.doc_id: (r["size"], r.text_crc32) for r in sh.shard(docs, 4).collect()}
    assert got == {i: (len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t, _, _ in ROWS}


def test_contamination(spark, docs):
    end = " ".join(PROSE.split()[-20:])
    items = [(7, end), (8, RUN)]
    got = sorted(((r.doc_id, r.n_words, r.n_hit, len(r["items"]), dc.items_digest(r["items"]), r.contaminated) for r in dc.find(docs, table(spark, items, "item_id long, text string")).collect()), key=repr)
    assert got == contamination([(i, t) for i, t, _, _ in ROWS], items)


def test_benchmark_of_many_windows_is_one_scan(spark, docs):
    """Hundreds of items of hundreds of words: one block, whose numbers take a few bytes a word."""
    items = [(i, " ".join(rng.choice(WORDS) for _ in range(300))) for i in range(400)]
    blocks = list(dc.pattern_blocks(table(spark, items, "item_id long, text string")))
    assert len(blocks) == 1 and blocks[0]["numbers"].nbytes == 4 * 300 * 400 and len(blocks[0]["words"]) <= len(WORDS)
    parts = list(dc.pattern_blocks(table(spark, [(1, PROSE)], "item_id long, text string"), most=1 << 20))
    windows = sum(len(p["numbers"]) - 12 * len(p["ends"]) for p in parts)
    assert len(parts) > 10 and windows == 18_000 * 12 - 12


def test_quality(docs):
    got = {r.doc_id: r for r in qr.measured(docs).collect()}
    assert (got[1].n_words, got[1].word_chars, got[1].n_dup_lines) == (216_000, len(PROSE) - PROSE.count(" ") - PROSE.count("\n"), 0)
    assert (got[2].n_words, got[2].word_chars, got[2].base_failed) == (1, len(RUN), True)


NAMES = (
    "_id _th _gid _gth _gone _lines _rate _source _cdf _bytes _share _u _chunk _first _own own own_ line pos h1 h2 site id th key component text_hash component_id "
    "_at _of _p _before _tie bad _bad _key text_key label bands signature set_hash copies_ salt _raw raw __id estimate row_no_ own__"
).split()


def test_clashing_names(spark):
    good = " ".join(WORDS[:60])
    rows = [(i, f"{good} {WORDS[100 + i]}" if i % 2 else f"{' '.join(WORDS[200 + 40 * i:240 + 40 * i])} same line\nsame line {i}", "en", f"s{i % 7}", *[f"{n}{i}" for n in NAMES]) for i in range(20)]
    plain = table(spark, [r[:4] for r in rows], SCHEMA)
    docs = table(spark, rows, SCHEMA + "".join(f", `{n}` string" for n in NAMES))
    kept = {r[0]: r[4:] for r in rows}
    same = lambda r: tuple(r[n] for n in NAMES) == kept[r["doc_id"]]
    for f in (
        lambda d: ld.strip_boilerplate(d, min_sites=2), lambda d: sm.mix(d), lambda d: md.keep_one_of_each(d), lambda d: qr.keep_good(d),
        lambda d: dc.keep_clean(d, spark.read.parquet(f"{SF}/benchmark.parquet")), lambda d: sh.shard(d, 4, keep=tuple(d.columns)),
    ):
        got, want = f(docs).collect(), f(plain).collect()
        assert sorted(r.doc_id for r in got) == sorted(r.doc_id for r in want) and all(map(same, got))
    for f in (md.near_duplicates, sd.cut_repeats, lambda d: tc.token_counts(d, tokenizer_path("byte_bpe_50k.json")), qr.measured, lambda d: sm.mix(d).select("doc_id", "copy")):
        assert sorted(map(repr, f(docs).collect())) == sorted(map(repr, f(plain).collect()))
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, SF)
        assert name == "sharding" or out.columns == docs.columns
        assert all(map(same, out.collect()))


def test_salted_lines_and_own_columns(spark, monkeypatch):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    read = lambda: sorted((r.doc_id, r.n_removed) for r in ld.strip_boilerplate(docs).collect())
    want = read()
    monkeypatch.setattr(ld, "BROADCAST_LINES", 0)
    assert read() == want
    clash = docs.selectExpr("*", "'x' AS shard", "'y' AS slot", "'z' AS row_no", "7 AS size")
    a = sorted((r.doc_id, r.shard, r.slot, r["size"]) for r in sh.shard(clash, 5, keep=tuple(clash.columns)).collect())
    assert a == sorted((r.doc_id, r.shard, r.slot, r["size"]) for r in sh.shard(docs, 5).collect())


def test_equal_rows_are_dealt_to_many_tasks(spark):
    docs = spark.range(20_000, numPartitions=8).selectExpr("CAST(NULL AS LONG) AS doc_id", "CAST(NULL AS STRING) AS text")
    placed = sh.numbered(docs.selectExpr("doc_id", "1L AS size", "0L AS text_crc32"), ["doc_id", "text_crc32", "size"])
    shares = placed._table.selectExpr("spark_partition_id() AS p").groupBy("p").count().collect()
    numbers = sorted(r.row_no for r in placed.collect())
    assert numbers == list(range(20_000)) and max(r["count"] for r in shares) < 15_000


def test_one_stranger_beside_many_near_copies(spark, monkeypatch):
    """A bucket of 20,000 near copies and one text below the threshold costs its rows a few times, not their square."""
    base = WORDS[:60]
    rows = [(i, " ".join([*base[:-1], f"tail{i}"])) for i in range(1, 20_001)]
    stranger = list(base)
    stranger[15], stranger[40] = "other", "words"
    rows.append((0, " ".join(stranger)))
    dealt, block_pairs = [], md.block_pairs

    def counted(*args):
        out = block_pairs(*args)
        dealt.append(out.count())
        return out

    monkeypatch.setattr(md, "block_pairs", counted)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(8)
    got = {r.doc_id: (r.component_id, r.kept) for r in md.near_duplicates(docs).collect()}
    assert got == {0: (0, True)} | {i: (1, i == 1) for i in range(1, 20_001)}
    assert dealt and all(n <= md.BANDS * 3 * len(rows) for n in dealt)


def test_order_follows_the_rows_of_a_task():
    rules = {"long": lambda m: m.n_words > 50, "stutter": lambda m: m.n_stutters > 3, "loud": lambda m: m.upper > m.lower}
    loud, long_ = "LOUD TEXT HERE", "many words " * 40
    first, second = qr.Cascade(rules), qr.Cascade(rules)
    for _ in range(qr.SAMPLE_FIRST):
        assert first.rejects(qr.Measured(loud)) and second.rejects(qr.Measured(long_))
    assert first.order[0] == "loud" and second.order[0] == "long"
    for i in range(5 * qr.SAMPLE_EACH):  # the data change within the task, and the order with them
        first.rejects(qr.Measured(long_))
    assert first.estimates()["long"][0] > 0 and first.sampled == qr.SAMPLE_FIRST + 5


def test_estimates_sample_all_of_a_sorted_table(spark):
    rows = [(i, ("LOUD TEXT OF TEN WORDS AND MORE THAN THAT FOR ALL " if i < 2000 else "quiet text of ten words and more than that for all ") + str(i), f"s{i // 1000}") for i in range(4000)]
    got = {r.rule: r for r in qr.estimates(table(spark, rows, "doc_id long, text string, source string"), one_of=8).collect()}
    assert set(got) == set(qr.BASE_RULES | qr.RULES)
    assert 350 < got["capitals"]["rows"] < 650 and 0.4 < got["capitals"].rejected / got["capitals"]["rows"] < 0.6
    assert np.isfinite(got["capitals"].seconds)
