"""Language identification with error-correcting output codes.

Each language has a codeword of +1 and -1; for each bit a binary classifier over hashed byte 2- and 3-grams
tells languages with +1 from those with -1. A classifier's weights are the log odds of the n-gram's
smoothed frequencies on its two sides, each language counting alike. Up to seven languages get the exhaustive code, more
get the best of several seeded random codes. A text's margins (mean log odds of its n-grams, times the
number of them up to ``EVIDENCE``) go into a logistic loss against each codeword, weighted for each
language and bit by how often that bit was right for that language in training; the least loss
wins, and the score is the soft minimum's share. A near tie is flagged as ambiguous.

Training counts n-grams over a sample of labelled rows: about ``TRAIN_ROWS``, chosen by a hash of
doc_id and text, whole texts each. The driver gets the counts of one label after the other and keeps a sum for each bit's two sides: bits times
``4 * DIMENSIONS`` numbers, and the bits grow with the logarithm of the number of labels. Any number of labels will do.
Prediction is local to a row: whole texts, no shuffle. Very long texts are counted and scored in blocks of ``BLOCK`` weights, so a text needs
a few bytes a byte.

A null text, or one without a letter, is ``und`` with score 0; so is every text if nothing could be
learned. Null labels aren't learned from; repeated rows and ties are harmless (ties go to the
language first in order); an empty table gives no rows. Only doc_id, text and lang are read, so other columns may have any name.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from finegrain.llm.common import bounded, written
from finegrain.llm.packed import pack_arrays, unpack_arrays

TRAIN_ROWS = 20_000
DIMENSIONS = 1 << 16
COMPARED = 2000
LABELS_AT_ONCE = 200
EVIDENCE = 60
AMBIGUOUS = 0.7
CHUNK = 1 << 20
BLOCK = 1 << 20
HELD_OUT_MOD = 5


def letters_only() -> bytes:
    """Byte table: ASCII letters in lower case, other ASCII blank, the rest as it is."""
    return bytes((c | 32) if 65 <= c <= 90 or 97 <= c <= 122 else 32 if c < 128 else c for c in range(256))


def spelled(texts: list[str | None], table: bytes) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of the texts one after the other, and where each starts.

    A text is set between blanks, so its n-grams don't depend on its neighbours.
    """
    parts, starts, at = [], [], 0
    for t in texts:
        raw = b" " + (t or "").lower().encode("utf-8", "surrogatepass").translate(table) + b"   "
        starts.append(at)
        at += len(raw)
        parts.append(raw)
    return np.frombuffer(b"".join([*parts, b"  "]), np.uint8), np.array(starts, np.int64)


def grams(spelling: np.ndarray, first: int, last: int) -> tuple[np.ndarray, np.ndarray]:
    """2-gram and 3-gram numbers (each below DIMENSIONS) at the bytes first..last-1."""
    b = spelling[first : last + 2].astype(np.uint32)
    two = (b[:-2] << np.uint32(8)) | b[1:-1]
    return two, ((two * np.uint32(0x9E3779B1) + b[2:] * np.uint32(0x85EBCA6B)) >> np.uint32(16)).astype(np.uint32)


def blocks(spelling: np.ndarray, size: int) -> Iterator[tuple[int, int]]:
    """Ranges of all bytes that have n-grams, ``size`` at most each."""
    for a in range(0, len(spelling) - 2, size):
        yield a, min(a + size, len(spelling) - 2)


def chunks(cells: list[str | None]) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about CHUNK characters."""
    start, size = 0, 0
    for i, t in enumerate(cells):
        size += len(t or "") + 8
        if size >= CHUNK:
            yield start, i + 1
            start, size = i + 1, 0
    if start < len(cells):
        yield start, len(cells)


def codewords(n: int, seed: int = 1) -> np.ndarray:
    """A row of +1 and -1 for each of n languages: distinct rows, no constant or repeated columns."""
    if n < 2:
        return np.ones((n, 1))
    if n <= 7:  # every split in two, once: the first language is always on the side of +1
        columns = np.arange(1, 2 ** (n - 1))
        rest = 1 - 2 * ((columns[None, :] >> np.arange(n - 1)[:, None]) & 1)
        return np.vstack([np.ones(len(columns), int), rest]).astype(float)
    rng, best, apart = np.random.default_rng(seed), None, -1
    for _ in range(50):
        code = rng.choice([-1.0, 1.0], (n, int(np.ceil(10 * np.log2(n)))))
        code = code[:, np.abs(code.sum(0)) < n]
        if n > COMPARED:  # so many random words of this length are far apart as they are
            if len(np.unique(code, axis=0)) == n:
                return code
            continue
        distance = (code.shape[1] - code @ code.T) / 2
        np.fill_diagonal(distance, np.inf)
        if distance.min() > apart:
            best, apart = code, distance.min()
    return best


class Model(NamedTuple):
    """Codewords, weights (2-grams, then 3-grams) of each bit's classifier, and decoding weights.

    Tasks get it as a plain tuple, as workers needn't have this package.
    """

    languages: list[str]
    code: np.ndarray
    weights: np.ndarray
    trust: np.ndarray

    def margins(self, texts: list[str | None], table: bytes) -> np.ndarray:
        spelling, starts = spelled(texts, table)
        total = np.zeros((len(texts), self.code.shape[1]))
        for a, b in blocks(spelling, max(1024, BLOCK // self.code.shape[1])):
            two, three = grams(spelling, a, b)
            first = int(np.searchsorted(starts, a, "right")) - 1
            cuts = np.append(a, starts[first + 1 : np.searchsorted(starts, b)]) - a
            total[first : first + len(cuts)] += np.add.reduceat(self.weights[two] + self.weights[three + DIMENSIONS], cuts, axis=0, dtype=np.float64)
        size = np.diff(np.append(starts, len(spelling) - 2))[:, None]
        return total / (2 * size) * np.minimum(2 * size, EVIDENCE)

    def losses(self, margins: np.ndarray) -> np.ndarray:
        """For each text and language the weighted logistic loss of the margins against the codeword."""
        return np.stack([(np.logaddexp(0, -margins * c) * t).sum(1) for c, t in zip(self.code, self.trust, strict=True)], 1)

    def predict(self, texts: list[str | None], table: bytes) -> tuple[list[str], np.ndarray]:
        if not self.languages:
            return ["und"] * len(texts), np.zeros(len(texts))
        loss = self.losses(self.margins(texts, table)) * self.code.shape[1]
        share = np.exp(loss.min(1, keepdims=True) - loss)
        return [self.languages[i] for i in loss.argmin(1)], share.max(1) / share.sum(1)


def share_of(rows: int, known: int) -> int:
    """The bound below which a 63-bit hash chooses about ``rows`` of ``known`` rows."""
    return (rows << 63) // max(rows, known)


def labelled(docs: DataFrame, text: str = "text", label: str = "lang", rows: int = TRAIN_ROWS) -> DataFrame:
    """About ``rows`` rows with a text and a label, by a hash of doc_id and text: the same ones each time."""
    known = docs.where(F.col(text).isNotNull() & F.col(label).isNotNull())
    bound = share_of(rows, known.count())
    own = F.shiftrightunsigned(F.xxhash64("doc_id", text), 1)
    chosen = known if bound >> 63 else known.where(own < F.lit(bound))
    return chosen.select(F.col(text).alias("text"), F.col(label).cast("string").alias("label"))


def gram_counts(sample: DataFrame) -> DataFrame:
    """label, counts: the n-gram counts (2-grams, then 3-grams) of each label's texts, compressed."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, sums = letters_only(), {}
        for batch in batches:
            cells, labels = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for label in set(labels):
                mine = [t for t, x in zip(cells, labels, strict=True) if x == label]
                new = sums.setdefault(label, np.zeros(2 * DIMENSIONS, np.int64))
                for i, j in chunks(mine):
                    spelling, _ = spelled(mine[i:j], table)
                    for a, b in blocks(spelling, BLOCK):
                        two, three = grams(spelling, a, b)
                        new[:DIMENSIONS] += np.bincount(two, minlength=DIMENSIONS)
                        new[DIMENSIONS:] += np.bincount(three, minlength=DIMENSIONS)
            while len(sums) > LABELS_AT_ONCE:  # many labels: what has been counted goes on
                label, c = sums.popitem()
                yield packed(label, c)
        for label, c in sums.items():
            yield packed(label, c)

    def packed(label: str, c: np.ndarray) -> pa.RecordBatch:
        at = np.flatnonzero(c)
        return pa.RecordBatch.from_arrays([pa.array([label]), pa.array([pack_arrays(at.astype(np.int32), c[at])], pa.binary())], names=["label", "counts"])

    def add(table: pa.Table) -> pa.Table:
        total = np.zeros(2 * DIMENSIONS, np.int64)
        for p in table.column("counts").to_pylist():
            at, c = unpack_arrays(p, np.int32, np.int64)
            total[at] += c
        at = np.flatnonzero(total)
        return pa.table({"label": table.column("label")[:1], "counts": pa.array([pack_arrays(at.astype(np.int32), total[at])], pa.binary())})

    schema = "label string, counts binary"
    return sample.mapInArrow(count, schema).groupBy("label").applyInArrow(add, schema)


def train(docs: DataFrame, rows: int = TRAIN_ROWS) -> Model:
    """A model of the languages in docs (columns doc_id, text, lang)."""
    sample = labelled(bounded(docs), rows=rows)
    counted = written(gram_counts(sample))
    names = sorted(r[0] for r in counted.select("label").collect())
    code, place = codewords(len(names)), {x: i for i, x in enumerate(names)}
    sides = np.zeros((2, code.shape[1], 2 * DIMENSIONS))
    for label, counts in counted.toLocalIterator():
        at, c = unpack_arrays(counts, np.int32, np.int64)
        share = np.full(2 * DIMENSIONS, 0.5)
        share[at] += c
        share /= share.sum()
        sides[0, code[place[label]] > 0] += share
        sides[1, code[place[label]] < 0] += share
    members = np.stack([(code > 0).sum(0), (code < 0).sum(0)])
    weights = np.zeros((2 * DIMENSIONS, code.shape[1]), np.float32)
    told = (members > 0).all(0)
    for j in np.flatnonzero(told):
        weights[:, j] = np.log(sides[0, j] / members[0, j]) - np.log(sides[1, j] / members[1, j])
    model = Model(names, code, weights, np.full(code.shape, 1 / max(code.shape[1], 1)))
    return model._replace(trust=trust(sample, model)) if len(names) > 1 else model


def trust(sample: DataFrame, model: Model) -> np.ndarray:
    """How often each bit is right for each language, as shares that add up to 1 for a language."""
    shared = sample.sparkSession.sparkContext.broadcast(tuple(model))

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, table = Model(*shared.value), letters_only()
        place = {x: i for i, x in enumerate(m.languages)}
        right, n = np.zeros(m.code.shape), np.zeros(len(m.languages))
        for batch in batches:
            cells, labels = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for a, b in chunks(cells):
                at = np.array([place[x] for x in labels[a:b]])
                np.add.at(right, at, m.margins(cells[a:b], table) * m.code[at] > 0)
                np.add.at(n, at, 1)
        rows = [(i, j, int(right[i, j]), int(n[i])) for i in range(right.shape[0]) for j in range(right.shape[1]) if n[i]]
        columns = list(zip(*rows, strict=True)) or [[]] * 4
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["i", "j", "ok", "n"])

    out = np.zeros(model.code.shape)
    for i, j, ok, n in sample.mapInArrow(check, "i long, j long, ok long, n long").groupBy("i", "j").agg(F.sum("ok"), F.sum("n")).collect():
        out[i, j] = (ok + 1) / (n + 2)
    return out / out.sum(1, keepdims=True)


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, lang_pred, score, ambiguous."""
    shared = docs.sparkSession.sparkContext.broadcast(tuple(model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, table = Model(*shared.value), letters_only()
        for batch in batches:
            cells = batch.column(1).to_pylist()
            names, scores = [], []
            for a, b in chunks(cells):
                got, share = m.predict(cells[a:b], table)
                plain = [t is None or not (t.isalpha() or any(map(str.isalpha, t))) for t in cells[a:b]]
                names += ["und" if p else g for g, p in zip(got, plain, strict=True)]
                scores.append(np.where(plain, 0.0, share))
            score = np.concatenate(scores) if scores else np.zeros(0)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, pa.string()), pa.array(score), pa.array(score < AMBIGUOUS)], names=["doc_id", "lang_pred", "score", "ambiguous"])

    return bounded(docs).selectExpr("CAST(doc_id AS LONG) AS doc_id", "text").mapInArrow(run, "doc_id long, lang_pred string, score double, ambiguous boolean")


def held_out(mod: int = HELD_OUT_MOD) -> Column:
    return F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % mod == 0
