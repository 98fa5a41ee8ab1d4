"""Benchmark decontamination with one Aho-Corasick automaton.

Texts are normalised by a byte table: A-Z become lower case, ASCII characters that are neither letter
nor digit become blanks, the rest stays. The table keeps offsets: byte k of the normalised text is byte
k of the original. Words of the benchmark have numbers, and the automaton holds each window of ``WINDOW`` consecutive words of an item (an item
of fewer words, but not none, is one window) as a string of a character for each word; one scan of a document's words (those
that no item has are character 0) finds all occurrences of all windows. A word inside an occurrence is hit.

What reaches the executors is the items' words as numbers, a few bytes a word. The automaton takes about 50 bytes for each word of
each window and is built once in each Python worker. ``PATTERN_BYTES`` of windows need about 0.8 GB there; beyond that, items go into
further automata of that size at most (a longer item in overlapping parts), each scanned once, and the hits of a document are put
together. A document's own scan is linear in its length and needs no other document.

Null and empty texts have no words and are clean; items without words match nothing; items with a null id
count as hits, but not as items; repeated items count once. Documents repeat as they are, ties don't matter. An empty
benchmark leaves every document clean, an empty table gives no rows. Very long texts are scanned whole, with about 100 bytes for
each of their words. ``find`` reads doc_id and text only; ``keep_clean`` keeps all columns of docs, whatever their names.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from finegrain.llm.common import bounded

WINDOW = 13
PATTERN_BYTES = 128 << 20
NEAR = 20  # contaminated: a 20th of the words or more


def word_table() -> bytes:
    """The byte table of the normal form."""
    out = bytearray(range(256))
    for c in range(128):
        if not chr(c).isalnum():
            out[c] = 32
        elif 65 <= c <= 90:
            out[c] = c + 32
    return bytes(out)


def words_of(text: str | None, table: bytes) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(table).split()


def pattern_blocks(items: DataFrame, size: int = WINDOW, most: int = PATTERN_BYTES) -> Iterator[dict]:
    """Blocks of items of about ``most`` bytes of windows each at most, as plain data: their distinct words, the parts of items as
    numbers of words from 1 (``ends`` tells where each part ends), each part's item id (None where null) and the window's size."""
    table = word_table()
    number: dict[bytes, int] = {}
    parts, ids, held = [], [], 0

    def block() -> dict:
        ends = np.cumsum([len(x) for x in parts], dtype=np.int64)
        return {"words": list(number), "numbers": np.concatenate([np.zeros(0, np.int32), *parts]), "ends": ends, "ids": list(ids), "size": size}

    for item, text in items.selectExpr("CAST(item_id AS STRING)", "text").toLocalIterator():
        words = words_of(text, table)
        step = max(1, most // (8 * size))
        for at in range(0, max(len(words) - size + 1, min(len(words), 1)), step):
            own = words[at : at + step + size - 1]
            room = sum(map(len, own)) * min(size, len(own)) + len(own)
            if parts and held + room > most:
                yield block()
                number, parts, ids, held = {}, [], [], 0
            held += room
            parts.append(np.array([number.setdefault(w, len(number) + 1) for w in own], np.int32))
            ids.append(item)
    yield block()


CODES = 1_000_000  # numbers that one character can stand for


def code_point(n: int) -> str:
    """The character of a number below CODES; surrogates are left out."""
    return chr(n if n < 0xD800 else n + 0x800)


class Scanner:
    """Finds the windows of a block in texts: a word is a character (two, where the block has more than CODES words), so that the automaton runs on strings."""

    def __init__(self, block: dict):
        import ahocorasick

        self.table, size = word_table(), block["size"]
        n_words = len(block["words"])
        self.width = 1 if n_words < CODES else 2
        spell = code_point if self.width == 1 else lambda n: code_point(1 + n // (CODES - 1)) + code_point(1 + n % (CODES - 1))
        codes = [spell(n) for n in range(n_words + 1)]
        self.code = dict(zip(block["words"], codes[1:], strict=True))
        self.unknown = "\0" * self.width
        self.automaton = ahocorasick.Automaton(ahocorasick.STORE_INTS)
        self.lengths, self.ids, owners, start = [], block["ids"], [], 0
        for part, end in enumerate(block["ends"].tolist()):
            own = [codes[x] for x in block["numbers"][start:end].tolist()]
            n, start = min(size, len(own)), end
            for i in range(len(own) - n + 1):
                window = "".join(own[i : i + n])
                k = self.automaton.get(window, None)
                if k is None:
                    k = len(self.lengths)
                    self.automaton.add_word(window, k)
                    self.lengths.append(n)
                owners.append((k, part))
        self.some = bool(self.lengths)
        if self.some:
            self.automaton.make_automaton()
            self.stretch = re.compile("[^\0]{%d,}" % (min(self.lengths) * self.width))
        pairs = np.array(owners, np.int64).reshape(-1, 2)
        self.owners = pairs[np.argsort(pairs[:, 0], kind="stable"), 1]
        self.first = np.searchsorted(np.sort(pairs[:, 0]), np.arange(len(self.lengths) + 1))

    def scan(self, text: str | None) -> tuple[int, list[tuple[int, int]], set[str]]:
        """Words of the text, hit word ranges [from, to), ids of items."""
        words = words_of(text, self.table)
        if not words or not self.some:
            return len(words), [], set()
        get, unknown, width = self.code.get, self.unknown, self.width
        line = "".join([get(w, unknown) for w in words])
        # No window holds an unknown word, so only stretches of known ones are run through, each once.
        found = [hit for m in self.stretch.finditer(line) for hit in self.automaton.iter(line, m.start(), m.end())]
        if width > 1:  # of whole words only
            found = [(end // width, k) for end, k in found if end % width == width - 1]
        if not found:
            return len(words), [], set()
        ranges = [(end + 1 - self.lengths[k], end + 1) for end, k in found]
        parts = {int(o) for k in {k for _, k in found} for o in self.owners[self.first[k] : self.first[k + 1]]}
        return len(words), ranges, {i for i in (self.ids[o] for o in parts) if i is not None}


def word_offsets(text: str | None, table: bytes) -> np.ndarray:
    """Byte offsets [from, to) of each word in the original text."""
    raw = np.frombuffer(b" " + (text or "").encode("utf-8", "surrogatepass").translate(table) + b" ", np.uint8) != 32
    edges = np.flatnonzero(raw[1:] != raw[:-1])
    return edges.reshape(-1, 2)


def kept_scanner(shared: dict) -> Scanner:
    """The scanner of a broadcast block: built once in each Python worker, and kept with the block."""
    if "scanner" not in shared:
        shared["scanner"] = Scanner(shared)
    return shared["scanner"]


def joined(ranges: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Ranges put together where they meet."""
    out: list[list[int]] = []
    for a, b in sorted(ranges):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


FOUND = "doc_id long, n_words long, n_hit long, items array<string>, spans array<struct<start:long,end:long>>"


def scan_block(docs: DataFrame, block: dict, extra: str = "") -> DataFrame:
    """FOUND for each document and one block; spans are byte offsets of hit passages in the original text."""
    shared = docs.sparkSession.sparkContext.broadcast(block)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = kept_scanner(shared.value)
        kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
        for batch in batches:
            rows = []
            for cell in batch.column(1):
                text = cell.as_py()
                n, ranges, items = scanner.scan(text)
                hits = joined(ranges)
                at = word_offsets(text, scanner.table) if hits else None
                spans = [{"start": int(at[a][0]), "end": int(at[b - 1][1])} for a, b in hits]
                rows.append((n, sum(b - a for a, b in hits), sorted(items), spans))
            columns = list(zip(*rows, strict=True)) or [[]] * 4
            arrays = [pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.list_(pa.string())), pa.array(columns[3], kind)]
            yield pa.RecordBatch.from_arrays([batch.column(0), *arrays, *batch.columns[2:]], names=["doc_id", "n_words", "n_hit", "items", "spans", *batch.schema.names[2:]])

    return bounded(docs).mapInArrow(run, FOUND + extra)


def find(docs: DataFrame, items: DataFrame, size: int = WINDOW, most: int = PATTERN_BYTES) -> DataFrame:
    """FOUND, text_key (a hash of the text) and contaminated for each row of docs."""
    rows = docs.selectExpr("CAST(doc_id AS LONG) AS doc_id", "text", "md5(CAST(coalesce(text, '') AS BINARY)) AS text_key")
    blocks = list(pattern_blocks(items, size, most))
    parts = [scan_block(rows, b, ", text_key string") for b in blocks]
    found = parts[0]
    if len(parts) > 1:
        for p in parts[1:]:
            found = found.unionByName(p)
        # Equal rows have equal results, so doc_id and text say which belong together.
        merged = found.groupBy(F.col("doc_id").alias("_id"), F.col("text_key").alias("_key")).agg(
            F.max("n_words").alias("n_words"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"), F.flatten(F.collect_set("spans")).alias("spans"))
        whole = rows.join(merged, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("text_key") == F.col("_key"))).drop("_id", "_key")
        found = whole.mapInArrow(_recount, FOUND + ", text_key string")
    return found.withColumn("contaminated", (F.col("n_hit") > 0) & (NEAR * F.col("n_hit") >= F.col("n_words")))


def _recount(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Hits of several blocks together: the words inside any span."""
    table = word_table()
    for batch in batches:
        out = []
        for row in batch.to_pylist():
            spans = joined([(s["start"], s["end"]) for s in row["spans"]])
            at = word_offsets(row["text"], table) if spans else []
            hit = sum(int(np.searchsorted(at[:, 0], b) - np.searchsorted(at[:, 0], a)) for a, b in spans)
            out.append({"doc_id": row["doc_id"], "n_words": row["n_words"], "n_hit": hit, "items": row["items"], "spans": [{"start": a, "end": b} for a, b in spans], "text_key": row["text_key"]})
        kind = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("items", pa.list_(pa.string())), ("spans", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), ("text_key", pa.string())])
        yield pa.RecordBatch.from_pylist(out, schema=kind)


def keep_clean(docs: DataFrame, items: DataFrame) -> DataFrame:
    """The rows of docs, unchanged, that aren't contaminated; texts are scanned where they lie."""
    blocks = list(pattern_blocks(items))
    if len(blocks) == 1:
        shared, at = docs.sparkSession.sparkContext.broadcast(blocks[0]), docs.columns.index("text")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            scanner = kept_scanner(shared.value)
            for batch in batches:
                good = []
                for cell in batch.column(at):
                    n, ranges, _ = scanner.scan(cell.as_py())
                    hit = sum(b - a for a, b in joined(ranges))
                    good.append(not (hit and NEAR * hit >= n))
                yield batch.filter(pa.array(good, pa.bool_()))

        return bounded(docs).mapInArrow(run, T.StructType(docs.schema.fields))
    bad = find(docs, items).where("contaminated").select(F.struct(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), "text_key").alias("bad")).distinct()
    text_key = F.md5(F.coalesce(docs["text"], F.lit("")).cast("binary"))
    return docs.join(bad, F.struct(F.coalesce(docs["doc_id"].cast("long").cast("string"), F.lit("")), text_key) == bad["bad"], "left_anti")


def items_digest(ids: list[str]) -> str:
    return hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest()
