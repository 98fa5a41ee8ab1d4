r"""Exact token counts at every prefix of a text, for byte-level byte-pair encodings.

Within a piece of the pre-tokeniser, the encoding of each prefix ends in one token t such that the
encoding of what stands before t is the encoding of that shorter prefix. So one pass over the piece, from
left to right, finds for each prefix its last token: the one vocabulary entry that ends there and is
compatible with the last token before it (the two side by side encode to themselves). Its count is the count before it plus
one. The counts of a text are the pieces' counts added up, and answer "how many tokens has
this prefix" and "how much fits a budget" without encoding again.

``PrefixCounter`` keeps what it found for prefixes, pairs and pieces, so pieces that begin alike share their beginnings'
work (a table that is full is emptied, which bounds memory and changes no result). A special token inside a text is one token, as the library has it.

A null text is empty: 0 tokens. Every row is its own, so repeated rows and ties get equal results; nothing is shuffled. An empty table gives no
rows. Very long texts are counted whole, with some 60 bytes for each piece; a very long piece (a text without blanks) takes time in
proportion to its length, as an automaton tells which tokens end at each of its bytes. Only doc_id and text are read, so other columns may have any name.
"""

from __future__ import annotations

import json
from bisect import bisect_right
from collections.abc import Iterator
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame

from finegrain.llm.common import bounded

PIECES = 500_000
NODES = 1_000_000
PAIRS = 1_000_000
SHARED = 48  # bytes of the longest piece that shares its beginnings with others
LIMIT = 512
CONTRACTIONS = ("'s", "'t", "'re", "'ve", "'m", "'ll", "'d")


def byte_letters() -> dict[str, int]:
    """The printable letter that stands for each byte in the vocabulary file, by rule: printable Latin-1 characters
    stand for themselves, the rest follow from code point 256 on."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


def vocabulary(path: str) -> tuple[dict[bytes, int], list[tuple[int, int]], list[str]]:
    """Number of each token by its bytes (0-255 for bytes, then in the order of the merges), the two parts of each
    merge, and the special tokens."""
    file = json.load(open(path, encoding="utf-8"))
    letters = byte_letters()
    as_bytes = lambda s: bytes(letters[c] for c in s)
    numbers, parts = {bytes([b]): b for b in range(256)}, [(b, b) for b in range(256)]
    for pair in file["model"]["merges"]:
        left, right = map(as_bytes, pair if isinstance(pair, list) else pair.split(" "))
        if left + right in numbers:
            raise ValueError("a token with two merges: the prefix method needs one for each")
        numbers[left + right] = len(parts)
        parts.append((numbers[left], numbers[right]))
    return numbers, parts, [t["content"] for t in file["added_tokens"]]


class PrefixCounter:
    def __init__(self, path: str, pattern: str | None = None):
        import regex

        self.numbers, self.parts, self.special = vocabulary(path)
        self.merged = {a << 17 | b: i for i, (a, b) in enumerate(self.parts) if i > 255}
        self.longest = max(map(len, self.numbers))
        self.pattern = regex.compile(pattern or r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+""")
        self.cut = regex.compile("|".join(map(regex.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None
        self.pairs: dict[int, bool] = {}
        self.nodes: dict[bytes, int] = {}  # prefix -> its tokens << 17 | its last token
        self.pieces: dict[str, int] = {}
        self.automaton = None

    def compatible(self, left: int, right: int) -> bool:
        """Whether two tokens side by side stay two: no merge across their border comes before the merges that made them.

        The younger of the two is taken apart, on the side of the border, until a merge across the border is found that
        would have come first, or single bytes are left.
        """
        before = len(self.parts)
        while True:
            made = self.merged.get(left << 17 | right)
            if made is not None and made < before:
                return False
            if left > right:
                if left < 256:
                    return True
                before, left = left, self.parts[left][1]
            else:
                if right < 256:
                    return True
                before, right = right + 1, self.parts[right][0]

    def node(self, piece: bytes) -> int:
        """Tokens << 17 | last token of a prefix, and of all its own prefixes on the way."""
        nodes = self.nodes
        known = nodes.get(piece)
        if known is not None:
            return known
        if len(piece) > SHARED:
            return self.long_piece(piece)[-1]
        if len(nodes) + len(piece) > NODES:
            nodes.clear()
        done = len(piece) - 1
        while done and piece[:done] not in nodes:
            done -= 1
        numbers, pairs, longest = self.numbers, self.pairs, self.longest
        for end in range(done + 1, len(piece) + 1):
            for start in range(max(0, end - longest), end):
                token = numbers.get(piece[start:end])
                if token is None:
                    continue
                if start == 0:  # each token's string encodes to that token
                    nodes[piece[:end]] = 1 << 17 | token
                    break
                before = nodes[piece[:start]]
                key = (before & 0x1FFFF) << 17 | token
                fits = pairs.get(key)
                if fits is None:
                    if len(pairs) >= PAIRS:
                        pairs.clear()
                    fits = pairs[key] = self.compatible(before & 0x1FFFF, token)
                if fits:
                    nodes[piece[:end]] = ((before >> 17) + 1) << 17 | token
                    break
        return nodes[piece]

    def endings(self):
        """An automaton that tells which tokens end at each byte, longest first; built when the first long piece comes."""
        if self.automaton is None:
            import ahocorasick

            self.automaton = ahocorasick.Automaton(ahocorasick.STORE_ANY)
            for raw, token in self.numbers.items():
                self.automaton.add_word(raw.decode("latin-1"), (len(raw), token))
            self.automaton.make_automaton()
        return self.automaton

    def long_piece(self, piece: bytes) -> list[int]:
        """As node, for each prefix of a long piece: kept by length, as keeping the prefixes would take its square."""
        out, pairs = [0], self.pairs
        for last, (size, token) in self.endings().iter(piece.decode("latin-1")):
            if len(out) > last + 1:
                continue  # its last token is known
            before = out[last + 1 - size]
            if size <= last:
                key = (before & 0x1FFFF) << 17 | token
                fits = pairs.get(key)
                if fits is None:
                    if len(pairs) >= PAIRS:
                        pairs.clear()
                    fits = pairs[key] = self.compatible(before & 0x1FFFF, token)
                if not fits:
                    continue
            out.append(((before >> 17) + 1) << 17 | token)
        return out

    def byte_prefixes(self, piece: bytes) -> list[int]:
        """Tokens of each prefix of a piece, by its length in bytes from 0."""
        if len(piece) > SHARED:
            return [x >> 17 for x in self.long_piece(piece)]
        self.node(piece)
        return [0, *(self.node(piece[:end]) >> 17 for end in range(1, len(piece) + 1))]

    def __getitem__(self, piece: str) -> int:
        """Tokens of a whole piece."""
        known = self.pieces.get(piece)
        if known is None:
            if len(self.pieces) >= PIECES:
                self.pieces.clear()
            known = self.pieces[piece] = self.node(piece.encode("utf-8", "surrogatepass")) >> 17
        return known

    def segments(self, text: str) -> Iterator[tuple[str, bool]]:
        """Stretches of plain text, and special tokens."""
        at = 0
        for m in self.cut.finditer(text) if self.cut else ():
            if m.start() > at:
                yield text[at : m.start()], False
            yield m[0], True
            at = m.end()
        if at < len(text):
            yield text[at:], False

    def marks(self, text: str) -> tuple[list[int], list[int]]:
        """Ends of the pieces in characters, and the tokens up to each: the table that budget questions search."""
        ends, counts, at, n = [], [], 0, 0
        for part, special in self.segments(text):
            pieces = [part] if special else self.pattern.findall(part)
            for p in pieces:
                at += len(p)
                n += 1 if special else self[p]
                ends.append(at)
                counts.append(n)
        return ends, counts

    def count(self, text: str | None) -> int:
        text = text or ""
        if self.cut and self.cut.search(text):
            return sum(1 if special else sum(map(self.__getitem__, self.pattern.findall(part))) for part, special in self.segments(text))
        return sum(map(self.__getitem__, self.pattern.findall(text)))

    def prefixes(self, text: str | None) -> list[int]:
        """Tokens of text[:p] for p = 0..len(text): what the library gives for each of these prefixes."""
        out, n = [0], 0
        parts = list(self.segments(text or ""))
        for i, (part, special) in enumerate(parts):
            if special:  # its own proper prefixes were counted as plain text below
                n += 1
                out.append(n)
                if i + 1 == len(parts) or parts[i + 1][1]:
                    out += self._plain(self._before(parts, i + 1), n)
                continue
            follows = self._before(parts, i + 1)
            inside = [n + c for c in self._prefixes_plain(part + follows)]
            out += inside[1:]
            n = inside[len(part)]
            if i == 0 and not out:
                out = inside
        if parts and parts[0][1]:
            out[1:1] = self._plain(self._before(parts, 0), 0)
        return out

    def _before(self, parts: list[tuple[str, bool]], i: int) -> str:
        return parts[i][0][:-1] if i < len(parts) and parts[i][1] else ""

    def _plain(self, text: str, n: int) -> list[int]:
        return [n + c for c in self._prefixes_plain(text)[1:]]

    def _prefixes_plain(self, text: str) -> list[int]:
        """Tokens of each prefix of a text without special tokens."""
        out, n, at = [0] * (len(text) + 1), 0, 0
        blank_from, blank_n = -1, 0  # the run of white space that the prefix ends in, and the tokens before it
        for piece in self.pattern.findall(text):
            if piece.isspace() and blank_from >= 0 and at > blank_from:
                start, base = blank_from, blank_n  # a later piece of one run: cut short, the run is one piece
            else:
                start, base = at, n
            end = at + len(piece)
            if piece.isspace():
                blank_from, blank_n = (start, base)
            elif piece[0] == " " and blank_from >= 0:  # the run's last blank belongs to this word
                out[at + 1] = blank_n + self[text[blank_from : at + 1]]
                blank_from = -1
            else:
                blank_from = -1
            for p in range(max(at + 1, start + 1), end + 1):
                if piece[0] == " " and not piece.isspace() and p == at + 1 and out[p]:
                    continue
                head = text[start:p]
                out[p] = base + (sum(map(self.__getitem__, self.pattern.findall(head))) if piece.startswith("'") and p < end else self[head])
            n += self[piece]
            at = end
        return out

    def fit(self, text: str | None, budget: int) -> int:
        """Characters of the longest prefix of whole pieces, and of a part of the next one, that has ``budget`` tokens at most."""
        ends, counts = self.marks(text or "")
        i = bisect_right(counts, budget)
        at = ends[i - 1] if i else 0
        return at if i == len(ends) else at + self.part(text[at : ends[i]], budget - (counts[i - 1] if i else 0))

    def part(self, piece: str, budget: int) -> int:
        """Characters of the longest proper prefix of a piece that has ``budget`` tokens at most.

        0 for blanks, contractions and special tokens: cut short, these would be other pieces.
        """
        if budget <= 0 or piece.isspace() or piece[0] == "'" or piece in self.special:
            return 0
        tokens, found, size = self.byte_prefixes(piece.encode("utf-8", "surrogatepass")), 0, 0
        for n, c in enumerate(piece[:-1], 1):
            size += len(c.encode("utf-8", "surrogatepass"))
            if tokens[size] <= budget and (n > 1 or c != " "):
                found = n
        return found


def token_counts(docs: DataFrame, path: str, budget: int = LIMIT, prefixes: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit, fit_chars (longest prefix within the budget, see ``PrefixCounter.fit``) and, if asked for,
    prefix_tokens: the count at every prefix, by its length in characters from 0."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = PrefixCounter(path)
        find, get = counter.pattern.findall, counter.__getitem__
        for batch in batches:
            sizes, totals, fits, tables = [], [], [], []
            for cell in batch.column(1):
                text = cell.as_py() or ""
                raw = len(text.encode("utf-8", "surrogatepass"))
                if counter.cut and counter.cut.search(text):
                    ends, counts = counter.marks(text)
                else:
                    pieces = find(text)
                    counts = list(accumulate(map(get, pieces)))
                    ends = None
                total = counts[-1] if counts else 0
                if total > budget:
                    i = bisect_right(counts, budget)
                    fit = (ends[i - 1] if ends else sum(map(len, pieces[:i]))) if i else 0
                    fit += counter.part(text[fit : ends[i]] if ends else pieces[i], budget - (counts[i - 1] if i else 0))
                else:
                    fit = len(text)
                sizes.append(raw)
                totals.append(total)
                fits.append(fit)
                tables.append(counter.prefixes(text) if prefixes else None)
            columns = [pa.array(sizes, pa.int64()), pa.array(totals, pa.int64()), pa.array([t > budget for t in totals], pa.bool_()), pa.array(fits, pa.int64())]
            names = ["doc_id", "n_bytes", "n_tokens", "over_limit", "fit_chars"]
            if prefixes:
                columns.append(pa.array(tables, pa.list_(pa.int32())))
                names.append("prefix_tokens")
            yield pa.RecordBatch.from_arrays([batch.column(0), *columns], names=names)

    schema = "doc_id long, n_bytes long, n_tokens long, over_limit boolean, fit_chars long" + (", prefix_tokens array<int>" if prefixes else "")
    return bounded(docs).selectExpr("CAST(doc_id AS LONG) AS doc_id", "text").mapInArrow(run, schema)
