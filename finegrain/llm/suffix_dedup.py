"""Exact substring dedup with two-stage suffix sorting.

A byte of a document is removed if a string of ``LENGTH`` bytes that covers it also starts in a document
with a smaller doc_id.

*Dealing.* Each window of LENGTH bytes has an anchor: the least hash of its ``GRAM``-byte strings. Equal windows have
equal anchors, and neighbouring windows mostly share one, so a document is a row of pieces (windows with one
anchor, side by side). First chunks of documents ask which of their anchors occur in other chunks; only pieces
with a shared anchor take part further: each distinct piece of a chunk goes, once, to the bucket of its anchor, with the least doc_id that
has it. An anchor with very many different pieces (more than ``HOT_PIECES``: the edges of a passage that very many documents
have) is dealt by the windows themselves instead, so no bucket has to hold them all; such a window is a string of its own that meets its equals by its
hash and bytes, and has no suffixes to sort.

*Sorting.* A bucket puts its distinct pieces in one string, each ended by a terminator, and sorts the suffixes in two
stages: the suffixes smaller than their successors are sorted directly, by their first bytes; all others follow by one
scan over the buckets of first bytes in ascending order, in which each suffix places its predecessor at the
front of the predecessor's bucket. Adjacent common prefixes of LENGTH or more put equal windows in one class, and the
least doc_id of a class is where the string starts first.

*Cutting.* The first doc_ids go back to the chunks, and windows whose string starts in a smaller doc_id are removed.

Null doc_ids come after all others and aren't smaller than one another; equal doc_ids aren't smaller either: rows that
repeat keep their text. Null and empty texts, and texts shorter than LENGTH, lose nothing. An empty table gives no
rows. Periodic texts of any length make pieces of ``RUN`` windows at most. A very long text is one chunk, with about 15 bytes of memory for each of its
bytes. Only doc_id and text are read, so other columns may have any name.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from finegrain.llm.common import bucket_count, written
from finegrain.llm.packed import Chunk, answered, pack, pack_arrays, questions, replies_of, total_bytes, unpack_arrays, unpack_chunks

LENGTH = 50
GRAM = 16
RUN = 64
HOT_PIECES = 4096
CHUNK_BYTES = 4 << 20
BUCKET_BYTES = 1 << 20
BLOCK = 1 << 18
SORT_BYTES = 1 << 19
PIECES_AT_ONCE = 1 << 16
LAST = np.int64(2**63 - 1)


def words_at(raw: bytes) -> np.ndarray:
    """The eight bytes from each position on, as a number (little-endian; zeros after the end)."""
    n = len(raw)
    padded = raw + bytes(16)
    out = np.empty(n + 8 - n % 8, np.uint64)
    for o in range(8):
        out[o::8] = np.frombuffer(padded, "<u8", len(out) // 8, o)
    return out[:n]


def words_of(raw: bytes) -> np.ndarray:
    """As words_at, without a copy: a view of each position's eight bytes, to be picked from."""
    return np.ndarray((len(raw),), "<u8", raw + bytes(8), 0, (1,))


def gram_hashes(words: np.ndarray) -> np.ndarray:
    """A hash of the GRAM (16) bytes from each position on."""
    later = np.zeros_like(words)
    later[:-8] = words[8:]
    h = words * np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(29)
    h += later * np.uint64(0xC2B2AE3D27D4EB4F)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    h *= np.uint64(0x94D049BB133111EB)
    return h


def sliding_min(h: np.ndarray, width: int) -> np.ndarray:
    span = 1
    while span * 2 <= width:
        h = np.minimum(h[:-span], h[span:])
        span *= 2
    return np.minimum(h[: len(h) - (width - span)], h[width - span :]) if span < width else h


def spread(least: np.ndarray) -> np.ndarray:
    """Least hashes are small numbers; mixed once more (one to one), they fall into all buckets alike."""
    least = (least ^ (least >> np.uint64(31))) * np.uint64(0x9FB21C651E98DF25)
    return least ^ (least >> np.uint64(28))


def pieces_of(chunk: Chunk, length: int = LENGTH) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Start, windows, anchor and document number of each piece, in the order of the body."""
    n = len(chunk.body)
    starts, counts, anchors = [], [], []
    sizes = np.diff(chunk.starts)
    valid_end = np.repeat((chunk.starts[1:] - length).astype(np.int32 if n < 2**31 else np.int64), sizes)  # last window of each byte's document
    opens = np.zeros(n, bool)
    opens[chunk.starts[:-1][sizes > 0]] = True
    width = length - GRAM + 1
    for at in range(0, max(n - length + 1, 0), BLOCK):
        upto = min(at + BLOCK, n - length + 1)
        low = sliding_min(gram_hashes(words_at(chunk.body[at : upto + length - 1]))[: upto - at + width - 1], width)
        here = np.arange(at, upto)
        good = here <= valid_end[at:upto]
        new = np.empty(len(low), bool)
        new[0] = True
        np.not_equal(low[1:], low[:-1], out=new[1:])
        new |= opens[at:upto]
        new[1:] |= good[1:] != good[:-1]
        edges = np.flatnonzero(new)
        spans = np.diff(np.append(edges, len(low)))
        if spans.max() > RUN:
            cut = -(-spans // RUN)
            base = np.repeat(edges, cut)
            step = np.arange(len(base)) - np.repeat(np.cumsum(cut) - cut, cut)
            edges = base + step * RUN
            spans = np.diff(np.append(edges, len(low)))
        keep = good[edges]
        starts.append(edges[keep] + at)
        counts.append(spans[keep])
        anchors.append(spread(low[edges[keep]]))
    if not starts:
        none = np.zeros(0, np.int64)
        return none, none, none.astype(np.uint64), none
    start = np.concatenate(starts)
    return start, np.concatenate(counts), np.concatenate(anchors), np.searchsorted(chunk.starts, start, "right") - 1


def owner_ids(chunk: Chunk) -> np.ndarray:
    return np.where(chunk.known, chunk.ids, LAST)


def bucket_of(keys: np.ndarray, buckets: int) -> np.ndarray:
    return ((keys >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int64)


def slices(bucket: np.ndarray) -> Iterator[tuple[int, slice]]:
    """The stretches of a sorted bucket column."""
    edges = np.flatnonzero(np.diff(bucket)) + 1
    for a, b in zip(np.append(0, edges), np.append(edges, len(bucket)), strict=True):
        if b > a:
            yield int(bucket[a]), slice(int(a), int(b))


def anchors_of(chunk: Chunk, found: tuple | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, tuple]:
    """Sorted distinct anchors, pieces of each (65,535 at most), whether several documents of this chunk have it, the pieces."""
    found = found or pieces_of(chunk)
    _, _, anchor, doc = found
    order = np.argsort(anchor, kind="stable")
    sorted_anchor, sorted_doc = anchor[order], doc[order]
    first = np.flatnonzero(np.append(True, sorted_anchor[1:] != sorted_anchor[:-1])) if len(anchor) else np.zeros(0, np.int64)
    if not len(first):
        return sorted_anchor, np.zeros(0, np.uint16), np.zeros(0, bool), found
    n = np.diff(np.append(first, len(anchor)))
    several = np.maximum.reduceat(sorted_doc, first) != np.minimum.reduceat(sorted_doc, first)
    return sorted_anchor[first], np.minimum(n, 65535).astype(np.uint16), several, found


def ask_anchors(buckets: int):
    def put(chunk: Chunk, _: dict) -> Iterator[tuple[int, bytes]]:
        keys, n, _, _ = anchors_of(chunk)
        low = keys.view(np.uint8).reshape(-1, 8)[:, :6]
        for b, s in slices(bucket_of(keys, buckets)):
            yield b, pack_arrays(low[s], n[s])

    return put


def answer_anchors(payloads: list[bytes]) -> list[bytes]:
    """For each anchor of each chunk: 1 if other chunks have it, 2 if it has very many pieces."""
    keys, sizes = [], []
    for p in payloads:
        low, n = unpack_arrays(p, np.uint8, np.uint16)
        key = np.zeros((len(n), 8), np.uint8)
        key[:, :6] = low.reshape(-1, 6)
        keys.append(key.view(np.uint64).ravel())
        sizes.append(n)
    every = np.concatenate(keys)
    _, inverse, chunks = np.unique(every, return_inverse=True, return_counts=True)
    pieces = np.bincount(inverse, np.concatenate(sizes))
    said = (chunks[inverse] > 1) * 1 + (pieces[inverse] > HOT_PIECES) * 2
    return [pack_arrays(x.astype(np.uint8)) for x in np.split(said, np.cumsum([len(k) for k in keys])[:-1])]


TAILS = np.array([(1 << 8 * n) - 1 for n in range(8)] + [2**64 - 1], np.uint64)


def content_hashes(words: np.ndarray, start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit hashes of the strings of ``size`` bytes at ``start``, from words_at of the bytes that hold them."""
    h1 = size.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    h2 = h1 ^ np.uint64(0x5851F42D4C957F2D)
    for k in range(0, int(size.max(initial=0)), 8):
        on = np.flatnonzero(size > k)
        w = words[start[on] + k] & TAILS[np.minimum(size[on] - k, 8)]
        x = (h1[on] ^ w) * np.uint64(0xBF58476D1CE4E5B9)
        h1[on] = x ^ (x >> np.uint64(31))
        y = (h2[on] + w) * np.uint64(0x94D049BB133111EB)
        h2[on] = y ^ (y >> np.uint64(29))
    return h1, h2


def distinct(words: np.ndarray, start: np.ndarray, size: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Equal strings once: the number of each string's class, a member of each class, the least owner of each, the classes' hash."""
    h1, h2 = content_hashes(words, start, size)
    order = np.lexsort((h2, h1))
    a, b = h1[order], h2[order]
    first = np.flatnonzero(np.append(True, (a[1:] != a[:-1]) | (b[1:] != b[:-1]))) if len(order) else np.zeros(0, np.int64)
    number = np.empty(len(order), np.int64)
    number[order] = np.repeat(np.arange(len(first)), np.diff(np.append(first, len(order))))
    least = np.minimum.reduceat(owner[order], first) if len(first) else owner
    return number, order[first], least, a[first]


def within(size: np.ndarray) -> np.ndarray:
    """0..size[0]-1, 0..size[1]-1 and so on, all in a row."""
    return np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)


@dataclass
class Part:
    """What a chunk asks about: distinct strings by key, and where its pieces find the answers.

    A piece asks one question, or one for each of its windows if its anchor is dealt by windows.
    """

    keys: np.ndarray  # of each question, ascending
    begin: np.ndarray  # where its string is in the chunk's body
    size: np.ndarray
    least: np.ndarray  # least owner in this chunk
    buckets: np.ndarray
    answers: np.ndarray  # for each window of each distinct piece the place of its answer, all in a row
    offset: np.ndarray  # where each distinct piece starts in answers
    piece: np.ndarray  # for each occurrence its piece,
    start: np.ndarray  # first byte,
    count: np.ndarray  # windows
    doc: np.ndarray  # and document


def taking_part(chunk: Chunk, replies: dict[int, bytes], buckets: int) -> Part:
    keys, _, several, (start, count, anchor, doc) = anchors_of(chunk)
    said = np.zeros(len(keys), np.uint8)
    for b, s in slices(bucket_of(keys, buckets)):
        said[s] = unpack_arrays(replies[b], np.uint8)[0]
    said[several] |= 1
    mine = said[np.searchsorted(keys, anchor)] if len(keys) else np.zeros(0, np.uint8)
    chosen = np.flatnonzero(mine & 1)
    start, count, doc, anchor, hot = start[chosen], count[chosen], doc[chosen], anchor[chosen], mine[chosen] > 1
    words = words_of(chunk.body)
    piece, member, least, _ = distinct(words, start, count + LENGTH - 1, owner_ids(chunk)[doc])
    at, windows, by_window = start[member], count[member], hot[member]
    plain = ~by_window
    # Windows of the pieces that are dealt by window.
    w_begin = np.repeat(at[by_window], windows[by_window]) + within(windows[by_window])
    w_number, w_member, w_least, w_key = distinct(words, w_begin, np.full(len(w_begin), LENGTH), np.repeat(least[by_window], windows[by_window]))
    ask_key = np.concatenate([anchor[member][plain], w_key])
    begin = np.concatenate([at[plain], w_begin[w_member]])
    asked = np.concatenate([windows[plain], np.ones(len(w_member), np.int64)])
    order = np.argsort(ask_key, kind="stable")
    place = np.zeros(len(order), np.int64)
    place[order] = np.cumsum(asked[order]) - asked[order]
    answers = np.zeros(int(windows.sum()), np.int64)
    of_plain = np.repeat(plain, windows)
    n = int(plain.sum())
    answers[of_plain] = np.repeat(place[:n], windows[plain]) + within(windows[plain])
    answers[~of_plain] = place[n:][w_number]
    return Part(
        ask_key[order], begin[order], asked[order] + LENGTH - 1, np.concatenate([least[plain], w_least])[order], bucket_of(ask_key[order], buckets),
        answers, np.cumsum(windows) - windows, piece, start, count, doc,
    )


def gathered(body: np.ndarray, begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The strings at begin, all in a row."""
    return body[np.repeat(begin, size) + within(size)]


def ask_pieces(buckets: int):
    def put(chunk: Chunk, replies: dict[str, dict[int, bytes]]) -> Iterator[tuple[int, bytes]]:
        part, body = taking_part(chunk, replies["shared"], buckets), np.frombuffer(chunk.body, np.uint8)
        for b, s in slices(part.buckets):
            yield b, pack_arrays(part.keys[s], part.least[s], part.size[s].astype(np.uint8), gathered(body, part.begin[s], part.size[s]))

    return put


def sorted_suffixes(raw: bytes, ends: np.ndarray) -> np.ndarray:
    """Positions of ``raw`` in the order of their suffixes, compared up to LENGTH bytes and to the end of their piece.

    ``ends`` are the places of the pieces' terminators. Ties come in any order.
    """
    n = len(raw)
    text = np.frombuffer(raw, np.uint8).astype(np.int16) + 1
    text[ends] = 0
    # A suffix is smaller than its successor if its first byte is, or if the bytes are equal and the successor is
    # smaller than its own: look for the next byte that differs.
    differs = np.flatnonzero(text[1:] != text[:-1])
    at = np.searchsorted(differs, np.arange(n - 1))
    following = text[np.append(differs, n - 2)[at] + 1]
    small = np.append((following > text[:-1]) & (text[:-1] > 0), False)
    chosen = np.flatnonzero(small)
    # First stage. Words of eight bytes, cut at the piece's end, compare as big-endian numbers.
    left = np.repeat(ends, np.diff(np.append(-1, ends)))[chosen] - chosen
    words = np.append(words_at(raw).byteswap(), np.zeros(LENGTH + 8, np.uint64))
    columns = []
    for k in range(0, LENGTH, 8):
        room = np.clip(left - k, 0, 8)
        columns.append(np.where(room > 0, words[chosen + k] & ~((np.uint64(1) << ((8 - room) * 8 % 64).astype(np.uint64)) - np.uint64(1)), np.uint64(0)))
    direct = chosen[np.lexsort(columns[::-1])]
    # Second stage. Buckets by first byte, in ascending order; each finished bucket places the predecessors of its
    # suffixes that are larger than them.
    by_first = np.searchsorted(text[direct], np.arange(258))
    waiting: list[list[np.ndarray]] = [[] for _ in range(257)]
    out = []
    for c in range(257):
        if c == 0:
            bucket = np.flatnonzero(text == 0)
        else:
            front = waiting[c]
            fresh = np.concatenate(front) if front else np.zeros(0, np.int64)
            whole = [fresh]
            while len(fresh):  # predecessors in the same bucket: runs of one byte
                before = fresh[fresh > 0] - 1
                fresh = before[text[before] == c]
                whole.append(fresh)
            bucket = np.concatenate([*whole, direct[by_first[c] : by_first[c + 1]]])
        out.append(bucket)
        before = bucket[bucket > 0] - 1
        before = before[text[before] > c]
        first = text[before]
        order = np.argsort(first, kind="stable")
        for b, s in slices(first[order]):
            waiting[b].append(before[order[s]])
    return np.concatenate(out)


def common_prefixes(raw: bytes, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Bytes that the suffixes at a and b have in common, LENGTH at most."""
    words = np.append(words_at(raw), np.zeros(LENGTH + 8, np.uint64))
    out, open_ = np.zeros(len(a), np.int64), np.arange(len(a))
    for k in range(0, LENGTH, 8):
        differ = words[a[open_] + k] ^ words[b[open_] + k]
        lowest = differ & (~differ + np.uint64(1))
        same = np.where(differ == 0, 8, (np.frexp(lowest.astype(np.float64))[1] - 1) // 8)
        out[open_] = k + same
        open_ = open_[differ == 0]
    return np.minimum(out, LENGTH)


def first_owners(pieces: np.ndarray, sizes: np.ndarray, owners: np.ndarray) -> np.ndarray:
    """For each window of each (distinct) piece, all in a row, the least owner of a piece that has it. pieces: their bytes in a row."""
    ends = np.cumsum(sizes + 1) - 1
    text = np.zeros(int(ends[-1]) + 1, np.uint8)
    inside = np.ones(len(text), bool)
    inside[ends] = False
    text[inside] = pieces
    raw = text.tobytes()
    order = sorted_suffixes(raw, ends)
    piece = np.repeat(np.arange(len(sizes)), sizes + 1)
    windows = order[ends[piece[order]] - order >= LENGTH]
    same = common_prefixes(raw, windows[:-1], windows[1:]) >= LENGTH
    first = np.flatnonzero(np.append(True, ~same))
    least = np.minimum.reduceat(owners[piece[windows]], first)
    out = np.zeros(len(raw), np.int64)
    out[windows] = np.repeat(least, np.diff(np.append(first, len(windows))))
    starts = np.zeros(len(raw), bool)
    starts[windows] = True
    return out[starts]


def answer_pieces(payloads: list[bytes]) -> list[bytes]:
    """For each piece of each chunk the first owner of each of its windows, all in a row."""
    parts = [unpack_arrays(p, np.uint64, np.int64, np.uint8, np.uint8) for p in payloads]
    key, least, size, raw = (np.concatenate(x) for x in zip(*parts, strict=True))
    each = [len(p[0]) for p in parts]
    del parts
    size = size.astype(np.int64)
    begin = np.cumsum(size) - size
    number, member, least, _ = distinct(words_of(raw.tobytes()), begin, size, least)
    order = np.argsort(key[member], kind="stable")  # pieces of one anchor side by side
    member, least = member[order], least[order]
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    number = rank[number]
    own_key, own_size = key[member], size[member]
    windows = own_size - LENGTH + 1
    offset = np.cumsum(windows) - windows
    result = np.repeat(least, windows)  # an anchor's only piece: its windows start where it does
    edges = np.flatnonzero(np.append(True, own_key[1:] != own_key[:-1]))
    pieces_of_key = np.diff(np.append(edges, len(own_key)))
    several = np.repeat(pieces_of_key > 1, pieces_of_key)
    # Groups of whole anchors with about SORT_BYTES of pieces.
    room = np.cumsum(np.where(several, own_size, 0))
    batch = np.repeat(room[edges] // SORT_BYTES, pieces_of_key)
    chosen = np.flatnonzero(several)
    for _, s in slices(batch[chosen]):
        own = chosen[s]
        at = np.repeat(offset[own], windows[own]) + within(windows[own])
        result[at] = first_owners(gathered(raw, begin[member[own]], own_size[own]), own_size[own], least[own])
    out, at = [], 0
    for n in each:
        mine = number[at : at + n]
        at += n
        w = windows[mine]
        out.append(pack_arrays(result[np.repeat(offset[mine], w) + within(w)]))
    return out


def removed_bytes(chunk: Chunk, shared: dict[int, bytes], firsts: dict[int, bytes], buckets: int) -> np.ndarray:
    """Whether each byte of the chunk's body is removed."""
    part = taking_part(chunk, shared, buckets)
    diff = np.zeros(len(chunk.body) + 1, np.int32)
    if len(part.piece):
        first_of = np.concatenate([unpack_arrays(firsts[b], np.int64)[0] for b, _ in slices(part.buckets)])
        owner = owner_ids(chunk)
        edges = np.append(np.arange(0, len(part.piece), PIECES_AT_ONCE), len(part.piece))
        for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
            count, step = part.count[a:b], within(part.count[a:b])
            first = first_of[part.answers[np.repeat(part.offset[part.piece[a:b]], count) + step]]
            where = (np.repeat(part.start[a:b], count) + step)[first < np.repeat(owner[part.doc[a:b]], count)]
            diff[where] += 1
            diff[where + LENGTH] -= 1
    return np.cumsum(diff[:-1], dtype=np.int32) > 0


def cut_repeats(docs: DataFrame, with_kept: bool = False, chunk_bytes: int = CHUNK_BYTES, bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    """doc_id, n_bytes, spans (removed byte ranges), kept_sha256 and, if asked for, kept (the bytes that stay).

    Chunks and buckets set the memory of a task (about 15 bytes for each byte of a chunk, 100 for each of a bucket) and
    the number of rows that are exchanged, chunks times buckets at most: larger executors should have larger ones.
    """
    chunks = pack(docs, size=chunk_bytes)
    buckets = bucket_count(total_bytes(chunks), bucket_bytes)
    shared = written(answered(questions(chunks, ask_anchors(buckets)), answer_anchors, "shared"))
    known = chunks.join(shared, "g", "left")
    firsts = answered(questions(known, ask_pieces(buckets), ("shared",)), answer_pieces, "firsts")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk, r in unpack_chunks(batch):
                gone = removed_bytes(chunk, replies_of(batch, r, "shared"), replies_of(batch, r, "firsts"), buckets)
                body = np.frombuffer(chunk.body, np.uint8)
                spans, digests, kept = [], [], []
                for a, b in zip(chunk.starts[:-1].tolist(), chunk.starts[1:].tolist(), strict=True):
                    own = gone[a:b]
                    if own.any():
                        edges = np.flatnonzero(np.diff(np.concatenate([[False], own, [False]]).astype(np.int8))).reshape(-1, 2)
                        spans.append([{"start": int(x), "end": int(y)} for x, y in edges])
                        left = body[a:b][~own].tobytes()
                    else:
                        spans.append([])
                        left = chunk.body[a:b]
                    digests.append(hashlib.sha256(left).hexdigest())
                    if with_kept:
                        kept.append(left)
                ids = pa.array(chunk.ids, pa.int64(), mask=~chunk.known)
                columns = [ids, pa.array(np.diff(chunk.starts), pa.int64()), pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), pa.array(digests, pa.string())]
                names = ["doc_id", "n_bytes", "spans", "kept_sha256"]
                if with_kept:
                    columns.append(pa.array(kept, pa.binary()))
                    names.append("kept")
                yield pa.RecordBatch.from_arrays(columns, names=names)

    whole = chunks.join(shared, "g", "left").join(firsts, "g", "left")
    schema = "doc_id long, n_bytes long, spans array<struct<start:long,end:long>>, kept_sha256 string" + (", kept binary" if with_kept else "")
    return whole.mapInArrow(run, schema)
