import random

from llm_helpers import SF, table
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from finegrain.llm import token_counts as tc
from finegrain.llm.queries import tokenizer_path

PATH = tokenizer_path("byte_bpe_50k.json")
LIBRARY, COUNTER = Tokenizer.from_file(PATH), tc.PrefixCounter(PATH)


def library(text):
    return len(LIBRARY.encode(text, add_special_tokens=False).ids)


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet=st.sampled_from("ab'stre  \n\tvé.1日 "), max_size=30) | st.text(max_size=20))
def test_every_prefix(text):
    assert COUNTER.prefixes(text) == [library(text[:p]) for p in range(len(text) + 1)]


def test_special_tokens_inside_texts():
    for text in ("<|endoftext|>", "a <|endoftext|> b", "<|endoftext|><|endoftext|>x", "x <|endoftext", " <|endoftext|>'re"):
        assert COUNTER.prefixes(text) == [library(text[:p]) for p in range(len(text) + 1)]
        assert COUNTER.count(text) == library(text)


def test_long_pieces_and_full_tables(monkeypatch):
    rng = random.Random(4)
    texts = ["x" * 5000, "".join(rng.choice("abé日") for _ in range(3000)), " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 12))) for _ in range(500))]
    monkeypatch.setattr(tc, "NODES", 200)
    monkeypatch.setattr(tc, "PIECES", 50)
    monkeypatch.setattr(tc, "PAIRS", 50)
    small = tc.PrefixCounter(PATH)
    assert [small.count(t) for t in texts] == [library(t) for t in texts]


def test_given_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    texts = {r.doc_id: r.text for r in docs.collect()}
    for r in tc.token_counts(docs, PATH, budget=100).collect():
        n = library(texts[r.doc_id])
        assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(texts[r.doc_id].encode()), n, n > 100)
        assert library(texts[r.doc_id][: r.fit_chars]) <= 100


def test_edges(spark):
    rows = [(None, None, 1), (1, "", 1), (2, "a b", 1), (2, "a b", 1)]
    docs = table(spark, rows, "doc_id long, text string, n_tokens long")
    out = tc.token_counts(docs, PATH, prefixes=True).collect()
    assert sorted(((r.doc_id, r.n_tokens, r.prefix_tokens) for r in out), key=repr) == [(1, 0, [0]), (2, 2, [0, 1, 2, 2]), (2, 2, [0, 1, 2, 2]), (None, 0, [0])]
    assert tc.token_counts(docs.limit(0), PATH).collect() == []
