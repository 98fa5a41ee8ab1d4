"""Quality rules in a short-circuit cascade.

Every rule looks at one document and rejects it or not; a document is kept if no rule rejects it. What a
rule costs and how much it rejects is estimated on a sample: in each task, the first ``SAMPLE_FIRST`` rows and every
``SAMPLE_EACH``-th go through all rules, with a clock, and the rules of the other rows run in the order of rejections per second found so far: most
documents that go are gone before an expensive rule sees them. So the order follows the data that a task really has (a table may be sorted by source),
no row is read twice and the driver gets nothing. ``estimates`` shows the figures of a whole table. The order never changes a verdict.

Words are runs of anything but ASCII white space, on the whole text. A null or empty text has no
words and fails the length rule. Repeated rows get the same verdict, nothing depends on other rows; ties in the order go to the cheaper rule, then by
name; an empty table gives no rows. A very long text is measured whole, with about 150 bytes for each word. ``measured`` reads doc_id and text only;
its base columns need the two base rules for every row, so only the other rules are ordered there. ``keep_good`` orders all rules and keeps all columns of
docs, whatever their names.
"""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from finegrain.llm.common import bounded

SAMPLE_FIRST, SAMPLE_EACH = 16, 128
MIN_WORDS = 10
WINDOW = 5
SYMBOLS = b"#*$%&|<>"
BLANK = b" \t\n\r\x0b\x0c"
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


class Measured:
    """A document's measures, each computed when a rule first asks for it."""

    def __init__(self, text: str | None):
        self.text = text or ""
        self.raw = self.text.encode("utf-8", "surrogatepass")
        self.words = self.raw.split()
        self.n_words = len(self.words)

    def __getattr__(self, name: str):
        made = getattr(Measured, "_" + name)(self)
        setattr(self, name, made)
        return made

    def _count(self, characters: bytes) -> int:
        return len(self.raw) - len(self.raw.translate(None, characters))

    def _word_chars(self) -> int:
        return len(self.text) - self._count(BLANK)

    def _n_symbols(self) -> int:
        return self._count(SYMBOLS)

    def _lines(self) -> list[bytes]:
        return [x for x in self.raw.split(b"\n") if x.strip()]

    def _n_dup_lines(self) -> int:
        return len(self.lines) - len(set(self.lines))

    def _n_repeat_words(self) -> int:
        n = self.n_words - WINDOW + 1
        if n < 2:
            return 0
        number: dict[bytes, int] = {}
        ids = np.fromiter((number.setdefault(w, len(number)) for w in self.words), np.uint64, self.n_words)
        mixed = np.zeros(n, np.uint64)
        for i in range(WINDOW):
            mixed = mixed * np.uint64(0x9E3779B97F4A7C15) + ids[i : i + n]
        order = np.sort(mixed)
        twice = order[1:][order[1:] == order[:-1]]
        if not len(twice):
            return 0
        at = np.flatnonzero(np.isin(mixed, twice))  # equal windows hash alike; the words decide
        windows = [tuple(self.words[i : i + WINDOW]) for i in at]
        times = Counter(windows)
        hit = np.zeros(self.n_words, bool)
        for i, w in zip(at, windows, strict=True):
            if times[w] > 1:
                hit[i : i + WINDOW] = True
        return int(hit.sum())

    def _n_stutters(self) -> int:
        return sum(map(bytes.__eq__, self.words[1:], self.words))

    def _upper(self) -> int:
        return self._count(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ")

    def _lower(self) -> int:
        return self._count(b"abcdefghijklmnopqrstuvwxyz")


Rules = dict[str, Callable[["Measured"], bool]]

#: A rule is true for a document that it rejects.
BASE_RULES: Rules = {
    "few_words": lambda m: m.n_words < MIN_WORDS,
    "repeated_windows": lambda m: 100 * m.n_repeat_words > 20 * m.n_words,
}
RULES: Rules = {
    "symbols": lambda m: 10 * m.n_symbols > m.n_words,
    "short_words": lambda m: m.word_chars < 2 * m.n_words,
    "long_words": lambda m: m.word_chars > 25 * m.n_words,
    "repeated_lines": lambda m: 2 * m.n_dup_lines > len(m.lines),
    "stutters": lambda m: 4 * m.n_stutters > m.n_words,
    "capitals": lambda m: m.upper > m.lower,
}


class Cascade:
    """The rules of a task, in the order of what its sampled rows have shown so far."""

    def __init__(self, rules: Rules, order: list[str] | None = None):
        self.rules, self.fixed, self.order = rules, order is not None, list(order or rules)
        self.seen, self.sampled = 0, 0
        self.gone, self.spent = dict.fromkeys(rules, 0), dict.fromkeys(rules, 0.0)

    def sample(self, text: str | None) -> list[str]:
        """The rules that reject a text: all are tried, each from the bare text on, so that none looks cheap for what another has measured."""
        out = []
        for name, rule in self.rules.items():
            m = Measured(text)
            began = time.perf_counter()
            rejects = rule(m)
            self.spent[name] += time.perf_counter() - began
            if rejects:
                self.gone[name] += 1
                out.append(name)
        self.sampled += 1
        return out

    def estimates(self) -> dict[str, tuple[float, float]]:
        """For each rule the share it rejects and its seconds a document."""
        n = max(self.sampled, 1)
        return {r: (self.gone[r] / n, self.spent[r] / n) for r in self.rules}

    def rejects(self, m: Measured) -> bool:
        self.seen += 1
        if not self.fixed and (self.seen <= SAMPLE_FIRST or self.seen % SAMPLE_EACH == 0):
            found = self.sample(m.text)
            self.order = cascade_order(self.estimates())
            return bool(found)
        return first_rejection(m, self.order, self.rules) is not None


def estimates(docs: DataFrame, rules: Rules | None = None, one_of: int = SAMPLE_EACH) -> DataFrame:
    """rule, rows, rejected, seconds over a sample of docs, one of ``one_of`` rows by a hash of doc_id and text; measured in the tasks."""
    rules = BASE_RULES | RULES if rules is None else rules
    schema = "rule string, rows long, rejected long, seconds double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cascade = Cascade(rules)
        for batch in batches:
            for text in batch.column(0):
                cascade.sample(text.as_py())
        names = list(rules)
        columns = [pa.array(names), pa.array([cascade.sampled] * len(names)), pa.array([cascade.gone[r] for r in names]), pa.array([cascade.spent[r] for r in names])]
        yield pa.RecordBatch.from_arrays(columns, names=["rule", "rows", "rejected", "seconds"])

    sample = bounded(docs).where(F.pmod(F.xxhash64("doc_id", "text"), F.lit(one_of)) == 0).select("text")
    sums = sample.mapInArrow(run, schema).groupBy("rule")
    return sums.agg(F.sum("rows").alias("rows"), F.sum("rejected").alias("rejected"), F.sum("seconds").alias("seconds"))


def cascade_order(estimates: dict[str, tuple[float, float]]) -> list[str]:
    """Rules by rejections per second, the most first."""
    return sorted(estimates, key=lambda r: (-estimates[r][0] / max(estimates[r][1], 1e-9), estimates[r][1], r))


def first_rejection(m: Measured, order: list[str], rules: Rules) -> str | None:
    return next((name for name in order if rules[name](m)), None)


def measured(docs: DataFrame, order: list[str] | None = None) -> DataFrame:
    """doc_id, the five measures, base_failed, kept: for documents that pass the base rules, the cascade's verdict."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cascade = Cascade(RULES, order)
        for batch in batches:
            rows = []
            for text in batch.column(1):
                m = Measured(text.as_py())
                failed = any(rule(m) for rule in BASE_RULES.values())
                rows.append([*(getattr(m, x) for x in MEASURES), failed, not failed and not cascade.rejects(m)])
            columns = [list(c) for c in zip(*rows, strict=True)] or [[]] * 7
            kinds = [pa.int64()] * 5 + [pa.bool_()] * 2
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], names=["doc_id", *MEASURES, "base_failed", "kept"])

    schema = f"doc_id long, {', '.join(f'{x} long' for x in MEASURES)}, base_failed boolean, kept boolean"
    return bounded(docs).selectExpr("CAST(doc_id AS LONG) AS doc_id", "text").mapInArrow(run, schema)


def keep_good(docs: DataFrame, order: list[str] | None = None) -> DataFrame:
    """The rows of docs, unchanged, that no rule rejects: all rules in one cascade, nothing computed twice."""
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cascade = Cascade(BASE_RULES | RULES, order)
        for batch in batches:
            good = [not cascade.rejects(Measured(t.as_py())) for t in batch.column(at)]
            yield batch.filter(pa.array(good, pa.bool_()))

    return bounded(docs).mapInArrow(run, T.StructType(docs.schema.fields))
