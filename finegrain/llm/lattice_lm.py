"""Language-model scores from a subword lattice.

The pieces of an existing vocabulary spell a text in many ways. The model draws pieces one by one, or the end; a
text's probability is the sum over all of its segmentations, by a forward recursion over byte positions in log space:
``alpha[j] = logsumexp(alpha[i] + log p(text[i:j]))``. Pieces don't cross word borders and each word begins with the
vocabulary's word mark, so a text's log probability is the sum of its words' and of the end's, and each distinct word
of the corpus is scored once.

A word of the training texts also has an arc of its own, from its begin to its end, beside its segmentations into
pieces: without it, a unigram model of pieces stays far behind one of words. Its weight is the word's discounted share of the training tokens;
the discounts' sum weights the pieces (see ``Arcs``). As the pieces then stand for words that are new, they are fitted to
the distinct training words, each once.

Weights start from the vocabulary's scores. A byte-pair vocabulary has ranks for scores; rank r starts at the Zipf weight
``1 / (r + ZIPF)``. Expectation maximisation over the distinct training words fits them, until a round
raises the training likelihood by less than a share ``GAIN`` or ``ROUNDS`` are done: expected uses of each piece come from the forward
and backward recursions, and are added up by piece, so what reaches the driver is bounded by the vocabulary. Vocabularies
with log probabilities start from these.

Words are runs of anything but ASCII white space, A-Z in lower case, each text followed by one end token.
Null and empty texts have the end only. Rows whose doc_id repeats are scored alike; a null doc_id counts as the empty
string when rows are held out. An empty table gives no rows; without training rows the starting weights score. Very long
texts are like others; a very long word (text without blanks) takes time in proportion to its length, and 8 bytes of memory a byte for each
recursion. Only doc_id and text are read (and what ``held_out`` names), so other columns may have any name.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from collections.abc import Iterator
from itertools import chain
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.llm.common import bucket_count, written
from finegrain.llm.packed import PART_BYTES, Chunk, pack, pack_arrays, questions, replies_of, split_buckets, total_bytes, unpack_arrays, unpack_chunks

ROUNDS = 20
GAIN = 0.01
ZIPF = 10.0
SMOOTH = 0.1
BUCKET_BYTES = 2 << 20
HELD_OUT = "CASE WHEN crc32(CAST(coalesce(CAST(doc_id AS STRING), '') AS BINARY)) % 7 = 2 THEN 1 ELSE 0 END"
WORD_MARK = "▁"
ROWS_AT_ONCE = 4096
LONG_WORD = 512
ARCS_AT_ONCE = 1 << 16
WORDS_AT_ONCE = 50_000
TASKS = 20_000


def lower_table() -> bytes:
    return bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def vocabulary(path: str) -> dict[bytes, float]:
    """Byte strings of the pieces and their starting log weights; the word mark is a blank."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    n = model.get_piece_size()
    scores = [model.get_score(i) for i in range(n)]
    ranked = any(s <= -100 and s == int(s) for s in scores)
    out: dict[bytes, float] = {}
    for i in range(n):
        piece = model.id_to_piece(i)
        if model.is_control(i) or model.is_unknown(i) or WORD_MARK in piece[1:] and not model.is_byte(i):
            continue
        if model.is_byte(i):
            raw, weight = bytes([int(piece[3:5], 16)]), -np.log(n + ZIPF) - 5
        else:
            raw = piece.replace(WORD_MARK, " ").encode()
            weight = -np.log(ZIPF - scores[i]) if ranked else scores[i]
        if raw not in out or weight > out[raw]:
            out[raw] = float(weight)
    total = np.logaddexp.reduce(np.array(list(out.values()) or [0.0]))
    return {p: w - float(total) for p, w in out.items()}


class Trie:
    """The pieces as one table: row = state, column = byte, 0 = no way on."""

    def __init__(self, pieces: list[bytes]):
        ways: dict[tuple[int, int], int] = {}
        ends = {}
        made = 1
        for number, piece in enumerate(pieces):
            state = 0
            for byte in piece:
                nxt = ways.get((state, byte))
                if nxt is None:
                    nxt = ways[state, byte] = made
                    made += 1
                state = nxt
            ends[state] = number
        self.table = np.zeros((made, 256), np.int32)
        at = np.array(list(ways), np.int64).reshape(-1, 2)
        self.table[at[:, 0], at[:, 1]] = list(ways.values())
        self.piece = np.full(made, -1, np.int32)
        self.piece[list(ends)] = list(ends.values())
        self.n = len(pieces)
        self.longest = max(map(len, pieces), default=0)


class Lattice:
    """All segmentations into pieces (a list, or their trie) with these log weights."""

    def __init__(self, pieces: list[bytes] | Trie, log_p: np.ndarray):
        self.trie = trie = Trie(pieces) if isinstance(pieces, list) else pieces
        self.n = trie.n
        self.table, self.piece = trie.table, trie.piece
        self.log_p = np.where(trie.piece >= 0, log_p[np.maximum(trie.piece, 0)] if trie.n else 0.0, -np.inf)

    def walk(self, text: np.ndarray, i: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """For rows of bytes: (end, rows, states) of all pieces that start at i."""
        rows, state = None, self.table[0, text[:, i]]
        for j in range(i, text.shape[1]):
            if j > i:
                state = self.table[state, text[rows, j]]
            alive = state > 0
            if not alive.all():
                rows = np.flatnonzero(alive) if rows is None else rows[alive]
                state = state[alive]
            elif rows is None:
                rows = np.arange(len(text))
            if not len(rows):
                return
            good = self.piece[state] >= 0
            yield (j + 1, rows, state) if good.all() else (j + 1, rows[good], state[good])

    def forward(self, text: np.ndarray) -> np.ndarray:
        alpha = np.full((text.shape[1] + 1, len(text)), -np.inf)
        alpha[0] = 0
        for i in range(text.shape[1]):
            for j, rows, state in self.walk(text, i):
                alpha[j, rows] = np.logaddexp(alpha[j, rows], alpha[i, rows] + self.log_p[state])
        return alpha

    def uses(self, text: np.ndarray, times: np.ndarray) -> np.ndarray:
        """Expected uses of each piece in rows of bytes that occur so many times."""
        return self.expected(text, times)[0]

    def expected(self, text: np.ndarray, times: np.ndarray) -> tuple[np.ndarray, float]:
        """The rows' uses of each piece, and their log likelihood."""
        alpha = self.forward(text)
        beta = np.full(alpha.shape, -np.inf)
        beta[-1] = 0
        states, shares = [np.zeros(0, np.int32)], [np.zeros(0)]
        for i in range(text.shape[1] - 1, -1, -1):
            before = alpha[i] - alpha[-1]
            for j, rows, state in self.walk(text, i):
                way = self.log_p[state] + beta[j, rows]
                beta[i, rows] = np.logaddexp(beta[i, rows], way)
                states.append(state)
                shares.append(np.exp(before[rows] + way) * times[rows])
        return np.bincount(self.piece[np.concatenate(states)], np.concatenate(shares), self.n), float(alpha[-1] @ times)

    def arcs(self, text: np.ndarray, first: int, last: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts, ends and states of all pieces in one text that start in first..last-1, by start, then end.

        All starts go on by one byte together, as often as the longest piece is long."""
        at = np.arange(first, last)
        state = self.table[0, text[first:last]]
        found = []
        for size in range(1, self.trie.longest + 1):
            alive = state > 0
            at, state = at[alive], state[alive]
            good = self.piece[state] >= 0
            found.append((at[good], np.full(int(good.sum()), size), state[good]))
            inside = at + size < len(text)
            at, state = at[inside], state[inside]
            if not len(at):
                break
            state = self.table[state, text[at + size]]
        starts, sizes, states = (np.concatenate(x) for x in zip(*found, strict=True))
        order = np.argsort(starts, kind="stable")
        return starts[order], (starts + sizes)[order], states[order]

    def forward_long(self, text: np.ndarray) -> np.ndarray:
        """alpha of one long text: its arcs are found for ARCS_AT_ONCE starts together, and added up one by one."""
        alpha = [-math.inf] * (len(text) + 1)
        alpha[0] = 0.0
        for first in range(0, len(text), ARCS_AT_ONCE):
            starts, ends, states = self.arcs(text, first, min(len(text), first + ARCS_AT_ONCE))
            for i, j, w in zip(starts.tolist(), ends.tolist(), self.log_p[states].tolist(), strict=True):
                alpha[j] = log_sum(alpha[j], alpha[i] + w)
        return np.array(alpha)

    def expected_long(self, text: np.ndarray, times: float) -> tuple[np.ndarray, float]:
        """As expected, for one long text."""
        alpha = self.forward_long(text)
        beta = [-math.inf] * (len(text) + 1)
        beta[-1] = 0.0
        out = np.zeros(self.n)
        for first in range((len(text) - 1) // ARCS_AT_ONCE * ARCS_AT_ONCE, -1, -ARCS_AT_ONCE):
            starts, ends, states = self.arcs(text, first, min(len(text), first + ARCS_AT_ONCE))
            log_p = self.log_p[states]
            for i, j, w in zip(starts[::-1].tolist(), ends[::-1].tolist(), log_p[::-1].tolist(), strict=True):
                beta[i] = log_sum(beta[i], w + beta[j])
            after = np.array([beta[j] for j in ends.tolist()])
            out += np.bincount(self.piece[states], np.exp(alpha[starts] + log_p + after - alpha[-1]) * times, self.n)
        return out, float(alpha[-1]) * times


def log_sum(a: float, b: float) -> float:
    if a < b:
        a, b = b, a
    return a if b == -math.inf else a + math.log1p(math.exp(b - a))


def by_length(words: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Numbers of words of one length, and their bytes with the word mark before them; long words come one by one."""
    sizes = np.array([len(w) for w in words], np.int64)
    order = np.argsort(sizes, kind="stable")
    edges = np.flatnonzero(np.diff(sizes[order])) + 1
    for a, b in zip(np.append(0, edges), np.append(edges, len(order)), strict=True):
        if b == a:
            continue
        size = int(sizes[order[a]])
        most = 1 if size > LONG_WORD else max(1, ROWS_AT_ONCE * 16 // (size + 16))
        for s in range(a, b, most):
            own = order[s : min(b, s + most)]
            yield own, np.frombuffer(b"".join([b" " + words[i] for i in own]), np.uint8).reshape(len(own), -1)


def word_log_p(lattice: Lattice, words: list[bytes]) -> np.ndarray:
    """Natural log of each word's marginal probability."""
    out = np.zeros(len(words))
    for own, text in by_length(words):
        out[own] = lattice.forward_long(text[0])[-1] if text.shape[1] > LONG_WORD else lattice.forward(text)[-1]
    return out


def word_uses(lattice: Lattice, words: list[bytes], times: np.ndarray) -> tuple[np.ndarray, float]:
    """Expected uses of each piece in the words, which occur so many times, and the words' log likelihood."""
    out, likelihood = np.zeros(lattice.n), 0.0
    for own, text in by_length(words):
        new, more = lattice.expected_long(text[0], float(times[own[0]])) if text.shape[1] > LONG_WORD else lattice.expected(text, times[own].astype(float))
        out, likelihood = out + new, likelihood + more
    return out, likelihood


def chunk_words(chunk: Chunk) -> list[list[bytes]]:
    """The words of each text of a chunk."""
    table = lower_table()
    return [chunk.text(i).translate(table).split() for i in range(len(chunk.ids))]


def dealt_words(texts: list[list[bytes]], buckets: int) -> tuple[list[bytes], np.ndarray]:
    """The distinct words, ordered by bucket, and their buckets: the same whenever a chunk is read."""
    words = list(dict.fromkeys(chain.from_iterable(texts)))
    bucket = np.fromiter((crc * buckets >> 32 for crc in map(zlib.crc32, words)), np.int64, len(words))
    order = np.argsort(bucket, kind="stable")
    return [words[i] for i in order.tolist()], bucket[order]


def bucket_edges(bucket: np.ndarray) -> Iterator[tuple[int, int, int]]:
    edges = np.flatnonzero(np.diff(bucket)) + 1
    for a, b in zip(np.append(0, edges).tolist(), np.append(edges, len(bucket)).tolist(), strict=True):
        if b > a:
            yield int(bucket[a]), a, b


def ask_words(buckets: int):
    def put(chunk: Chunk, _: dict) -> Iterator[tuple[int, bytes]]:
        texts = chunk_words(chunk)
        words, bucket = dealt_words(texts, buckets)
        learnt: Counter[bytes] = Counter()
        for tag, text in zip(chunk.tags.tolist(), texts, strict=True):
            if tag == 0:
                learnt.update(text)
        counts = np.fromiter(map(learnt.__getitem__, words), np.int64, len(words))
        for b, i, j in bucket_edges(bucket):
            yield b, pack_arrays(b" ".join(words[i:j]), counts[i:j])

    return put


def merged_words(asked: DataFrame, buckets: int = 8, each: int = PART_BYTES) -> DataFrame:
    """The corpus' words of each bucket b and their training counts; n: tokens, known: words with a count, once, twice: with that count.

    Parts of a bucket are merged first, so that a task gets about ``each`` bytes, and then as many rows as there are parts.
    """

    def merge(table: pa.Table) -> tuple[bytes, np.ndarray]:
        total: Counter[bytes] = Counter()
        for p in table.column("payload").to_pylist():
            words, counts = unpack_arrays(p, None, np.int64)
            for w, c in zip(words.split(b" "), counts.tolist(), strict=True):
                total[w] += c
        words = sorted(total)
        return b" ".join(words), np.array([total[w] for w in words], np.int64)

    def part(table: pa.Table) -> pa.Table:
        return pa.table({"b": table.column("b")[:1], "payload": pa.array([pack_arrays(*merge(table))], pa.binary())})

    def whole(table: pa.Table) -> pa.Table:
        words, counts = merge(table)
        sums = {"n": counts.sum(), "known": (counts > 0).sum(), "once": (counts == 1).sum(), "twice": (counts == 2).sum()}
        return pa.table({"b": table.column("b")[:1], "words": pa.array([pack_arrays(words, counts)], pa.binary()), **{k: pa.array([int(x)]) for k, x in sums.items()}})

    parts = split_buckets(asked, each)[0].groupBy("b", "s").applyInArrow(part, "b int, payload binary")
    # As many tasks as buckets: few bytes are much work for the rounds that read them, so their partitions must not be put together.
    tasks = min(TASKS, buckets)
    return written(parts.repartition(tasks, "b").groupBy("b").applyInArrow(whole, "b int, words binary, n long, known long, once long, twice long"))


def word_lists(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list[tuple[int, int]], list[bytes], np.ndarray]]:
    """The words of some buckets (columns b, words) together, WORDS_AT_ONCE or those of one bucket, as long runs are quicker:
    each bucket with the number of its words, the words, their counts."""
    sizes, words, counts = [], [], []
    for batch in batches:
        for b, p in zip(batch.column("b").to_pylist(), batch.column("words").to_pylist(), strict=True):
            blob, c = unpack_arrays(p, None, np.int64)
            sizes.append((b, len(c)))
            words += blob.split(b" ")
            counts.append(c)
            if len(words) >= WORDS_AT_ONCE:
                yield sizes, words, np.concatenate(counts)
                sizes, words, counts = [], [], []
    if words:
        yield sizes, words, np.concatenate(counts)


class Model(NamedTuple):
    """Plain data, so that it reaches workers that can't import this package; ``log_p`` is in the order of ``pieces``."""

    pieces: list[bytes]
    log_p: np.ndarray
    end: float
    likelihoods: list[float]  # of the training words and the end, before each round

    def end_log_p(self) -> float:
        """Log probability that a text ends where a word could begin, rather than goes on."""
        begins = [p[:1] == b" " for p in self.pieces]
        return self.end - float(np.logaddexp.reduce(np.append(self.log_p[begins], self.end)))


class Arcs(NamedTuple):
    """Weights of the arcs of whole words: a word that occurs c times in ``total`` training tokens has (c - discount) / total.

    What the discounts leave, ``rest``, goes to segmentations into pieces.
    """

    total: int
    discount: float
    rest: float

    @classmethod
    def of(cls, total: int, distinct: int, once: int, twice: int) -> Arcs:
        discount = min(0.9, max(0.1, once / (once + 2 * twice))) if once + twice else 0.5
        return cls(total, discount, discount * distinct / total if total else 1.0)

    def log_p(self, counts: np.ndarray, pieces: np.ndarray) -> np.ndarray:
        """Log probabilities of tokens from their counts and their log probabilities over the pieces."""
        whole = np.log(np.maximum(counts - self.discount, 0) / max(self.total, 1), out=np.full(len(counts), -np.inf), where=counts > 0)
        return np.logaddexp(whole, pieces + np.log(self.rest))


def kept_trie(shared: dict) -> Trie:
    """The trie of a broadcast dictionary's pieces: built once in each Python worker, and kept with the dictionary."""
    if "trie" not in shared:
        shared["trie"] = Trie(shared["pieces"])
    return shared["trie"]


def fit(words: DataFrame, ends: int, path: str, rounds: int = ROUNDS, gain: float = GAIN) -> Model:
    """Expectation maximisation over the words of merged_words, each of those with a count once; ``ends`` is how often the end counts.

    Stops after ``rounds`` rounds, or when a round has raised the training likelihood by less than a share ``gain`` of it.
    """
    start = vocabulary(path)
    pieces = sorted(start)
    log_p, end = np.array([start[p] for p in pieces]) + np.log(0.99), float(np.log(0.01))
    shared = words.sparkSession.sparkContext.broadcast({"pieces": pieces})
    likelihoods: list[float] = []
    for _ in range(rounds if ends else 0):

        def expect(batches: Iterator[pa.RecordBatch], log_p: np.ndarray = log_p) -> Iterator[pa.RecordBatch]:
            lattice = Lattice(kept_trie(shared.value), log_p)
            out, likelihood = np.zeros(lattice.n), 0.0
            for _, words, counts in word_lists(batches):
                known = [w for w, c in zip(words, counts.tolist(), strict=True) if c]
                new, more = word_uses(lattice, known, np.ones(len(known)))
                out, likelihood = out + new, likelihood + more
            at = np.flatnonzero(out)
            yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1).astype(np.int32)), pa.array(np.append(out[at], likelihood))], names=["piece", "uses"])

        got = words.where("known > 0").select("b", "words").mapInArrow(expect, "piece int, uses double").groupBy("piece").agg(F.sum("uses").alias("uses")).toArrow()
        at, sums = got.column("piece").to_numpy(), got.column("uses").to_numpy()
        uses = np.zeros(len(pieces))
        uses[at[at >= 0]] = sums[at >= 0]
        likelihoods.append(float(sums[at < 0].sum()) + ends * end)
        whole = np.log(uses.sum() + ends + SMOOTH * (len(pieces) + 1))
        log_p, end = np.log(uses + SMOOTH) - whole, float(np.log(ends + SMOOTH) - whole)
        if len(likelihoods) > 1 and likelihoods[-1] - likelihoods[-2] < gain * abs(likelihoods[-2]):
            break
    return Model(pieces, log_p, end, likelihoods)


def scores(docs: DataFrame, path: str, held_out: str = HELD_OUT, rounds: int = ROUNDS, each: int = PART_BYTES) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score (log10) for each row of docs.

    held_out is an SQL expression that is 1 for rows the model doesn't learn from.
    """
    chunks = pack(docs, held_out)
    buckets = bucket_count(total_bytes(chunks), BUCKET_BYTES)
    asked = written(questions(chunks, ask_words(buckets)))
    words = merged_words(asked, buckets, each)
    ends = docs.where(F.expr(held_out) == 0).count()
    n, known, once, twice = words.agg(*(F.coalesce(F.sum(c), F.lit(0)) for c in ("n", "known", "once", "twice"))).first()
    train_tokens, distinct = n + ends, known + (ends > 0)
    model, whole = fit(words, min(ends, 1), path, rounds), Arcs.of(train_tokens, distinct, once + (ends == 1), twice + (ends == 2))
    shared = docs.sparkSession.sparkContext.broadcast({"pieces": model.pieces, "log_p": model.log_p})
    end = float(whole.log_p(np.array([ends]), np.array([model.end_log_p()]))[0])

    def weigh(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lattice = Lattice(kept_trie(shared.value), shared.value["log_p"])
        for sizes, every, counts in word_lists(batches):
            log_p, start = whole.log_p(counts, word_log_p(lattice, every)), 0
            for b, n in sizes:
                mine, start = slice(start, start + n), start + n
                yield pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), pa.array([pack_arrays(b" ".join(every[mine]), counts[mine], log_p[mine])], pa.binary())], names=["b", "words"])

    weighed = written(words.select("b", "words").mapInArrow(weigh, "b int, words binary"))

    def answer(questions_: pa.Table, bucket: pa.Table) -> pa.Table:
        if not questions_.num_rows:  # a part that no question fell in
            return pa.table({"g": pa.array([], pa.int64()), "b": pa.array([], pa.int32()), "payload": pa.array([], pa.binary())})
        blob, counts, log_p = unpack_arrays(bucket.column("words")[0].as_py(), None, np.int64, np.float64)
        place = {w: i for i, w in enumerate(blob.split(b" "))}
        back = []
        for p in questions_.column("payload").to_pylist():
            mine = [place[w] for w in unpack_arrays(p, None, np.int64)[0].split(b" ")]
            back.append(pack_arrays(counts[mine], log_p[mine]))
        return pa.table({"g": questions_.column("g"), "b": questions_.column("b"), "payload": pa.array(back, pa.binary())})

    parted, many = split_buckets(asked, each)
    last = F.coalesce("parts", F.lit(1).cast("long")) - 1
    copied = weighed.join(many, "b", "left").select("b", "words", F.explode(F.sequence(F.lit(0).cast("long"), last)).alias("s"))
    back = parted.groupBy("b", "s").cogroup(copied.groupBy("b", "s")).applyInArrow(answer, "g long, b int, payload binary")
    told = back.groupBy("g").agg(F.collect_list(F.struct("b", "payload")).alias("replies"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ten = np.log(10)
        room = np.log10(train_tokens + distinct + 1)
        for batch in batches:
            for chunk, r in unpack_chunks(batch):
                replies = replies_of(batch, r)
                texts = chunk_words(chunk)
                every, bucket = dealt_words(texts, buckets)
                parts = [unpack_arrays(replies[b], np.int64, np.float64) for b, _, _ in bucket_edges(bucket)]
                count = np.concatenate([c for c, _ in parts]) if parts else np.zeros(0, np.int64)
                log_p = np.concatenate([x for _, x in parts]) / ten if parts else np.zeros(0)
                place = dict(zip(every, range(len(every)), strict=True))
                sizes = np.array([len(t) for t in texts])
                at = np.fromiter(map(place.__getitem__, chain.from_iterable(texts)), np.int64, int(sizes.sum()))
                owner = np.repeat(np.arange(len(texts)), sizes)
                add = lambda x: np.bincount(owner, x[at], len(texts))  # noqa: B023, E731
                arrays = [
                    pa.array(chunk.ids, pa.int64(), mask=~chunk.known), pa.array(chunk.tags == 1), pa.array(sizes + 1, pa.int64()),
                    pa.array(add(count > 0).astype(np.int64) + (ends > 0), pa.int64()), pa.array(np.full(len(texts), train_tokens, np.int64)),
                    pa.array(add(np.log10(count + 1) - room) + np.log10(ends + 1) - room), pa.array(add(log_p) + end / ten),
                ]
                yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    return chunks.join(told, "g", "left").mapInArrow(run, schema)
