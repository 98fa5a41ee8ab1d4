"""Chunks of documents, and questions that chunks put to partners found by a key.

Some operators ask about many small things of each document (a word's count in the corpus, where a
passage occurs first). A row for each would shuffle several times the text. Here documents are packed
into chunks of a few MB; a chunk asks about each distinct thing once, with the things of a bucket in
one compressed row, and gets one row back. A thing that every document has therefore costs a chunk one entry,
and a bucket as many entries as there are chunks, however often it occurs.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.llm.common import bounded, written

CHUNK_BYTES = 2 << 20
PART_BYTES = 32 << 20
CHUNK = "g long, ids binary, known binary, tags binary, sizes binary, body binary"


@dataclass
class Chunk:
    g: int
    ids: np.ndarray  # doc_id, 0 where null
    known: np.ndarray  # whether doc_id isn't null
    tags: np.ndarray  # one number for each document
    starts: np.ndarray  # where each text starts in body, and the end
    body: bytes  # UTF-8 of all texts

    def text(self, i: int) -> bytes:
        return self.body[self.starts[i] : self.starts[i + 1]]


def squeeze(data: bytes) -> bytes:
    import zstandard

    return zstandard.ZstdCompressor(level=3).compress(data)


def unsqueeze(data: bytes) -> bytes:
    import zstandard

    return zstandard.ZstdDecompressor().decompress(data)


def pack_arrays(*arrays: np.ndarray | bytes) -> bytes:
    """Arrays or bytes as one compressed string."""
    raw = [a if isinstance(a, bytes) else np.ascontiguousarray(a).tobytes() for a in arrays]
    return squeeze(np.array([len(raw), *map(len, raw)], np.int64).tobytes() + b"".join(raw))


def unpack_arrays(data: bytes, *kinds: type | str | None) -> list:
    raw, out = unsqueeze(data), []
    n = int(np.frombuffer(raw, np.int64, 1)[0])
    at = 8 * (n + 1)
    for size, kind in zip(np.frombuffer(raw, np.int64, n, 8), kinds, strict=True):
        part = raw[at : at + int(size)]
        out.append(part if kind is None else np.frombuffer(part, kind))
        at += int(size)
    return out


def pack(docs: DataFrame, tag: str = "0", size: int = CHUNK_BYTES) -> DataFrame:
    """A written table of chunks of docs (columns doc_id, text); ``tag`` is an SQL expression of docs' columns, a long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, made = TaskContext.get().partitionId(), 0
        held: list[list] = [[], [], []]
        room = 0

        def row() -> pa.RecordBatch:
            ids, tags, texts = held
            columns = [
                (part << 32) + made,
                np.array([0 if i is None else i for i in ids], np.int64).tobytes(),
                np.array([i is not None for i in ids], np.uint8).tobytes(),
                np.array(tags, np.int64).tobytes(),
                np.array([len(t) for t in texts], np.int64).tobytes(),
                squeeze(b"".join(texts)),
            ]
            kinds = [pa.int64()] + [pa.binary()] * 5
            return pa.RecordBatch.from_arrays([pa.array([c], k) for c, k in zip(columns, kinds, strict=True)], names=["g", "ids", "known", "tags", "sizes", "body"])

        for batch in batches:
            for i, t, x in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                raw = (t or "").encode("utf-8", "surrogatepass")
                held[0].append(i)
                held[1].append(x)
                held[2].append(raw)
                room += len(raw) + 64
                if room >= size:
                    yield row()
                    held, room, made = [[], [], []], 0, made + 1
        if held[0]:
            yield row()

    rows = bounded(docs).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text"), F.expr(tag).cast("long").alias("tag"))
    return written(rows.mapInArrow(run, CHUNK))


def unpack_chunks(batch: pa.RecordBatch) -> Iterator[tuple[Chunk, int]]:
    """Each chunk of a batch, and its row."""
    for r in range(batch.num_rows):
        get = lambda name, kind: np.frombuffer(batch.column(name)[r].as_py(), kind)  # noqa: B023, E731
        starts = np.concatenate([[0], np.cumsum(get("sizes", np.int64))])
        yield Chunk(batch.column("g")[r].as_py(), get("ids", np.int64), get("known", np.uint8) > 0, get("tags", np.int64), starts, unsqueeze(batch.column("body")[r].as_py())), r


def replies_of(batch: pa.RecordBatch, r: int, column: str = "replies") -> dict[int, bytes]:
    return {x["b"]: x["payload"] for x in batch.column(column)[r].as_py() or []}


def questions(chunks: DataFrame, put: Callable[[Chunk, dict[str, dict[int, bytes]]], Iterator[tuple[int, bytes]]], replies: tuple[str, ...] = ()) -> DataFrame:
    """g, b, payload: the (bucket, payload) pairs that ``put`` makes of each chunk and its earlier replies."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk, r in unpack_chunks(batch):
                rows = list(put(chunk, {c: replies_of(batch, r, c) for c in replies}))
                yield pa.RecordBatch.from_arrays([pa.array([chunk.g] * len(rows), pa.int64()), pa.array([b for b, _ in rows], pa.int32()), pa.array([p for _, p in rows], pa.binary())], names=["g", "b", "payload"])

    return chunks.mapInArrow(run, "g long, b int, payload binary")


def answered(asked: DataFrame, answer: Callable[[list[bytes]], list[bytes]], name: str = "replies") -> DataFrame:
    """g and an array of (b, payload): ``answer`` gets all payloads of a bucket and returns one for each."""

    def run(table: pa.Table) -> pa.Table:
        back = answer(table.column("payload").to_pylist())
        return pa.table({"g": table.column("g"), "b": table.column("b"), "payload": pa.array(back, pa.binary())})

    back = asked.groupBy("b").applyInArrow(run, "g long, b int, payload binary")
    return back.groupBy("g").agg(F.collect_list(F.struct("b", "payload")).alias(name))


def split_buckets(asked: DataFrame, each: int = PART_BYTES) -> tuple[DataFrame, DataFrame]:
    """asked (a written table) with ``s``, the part of its bucket that a question is in, and b, parts of the buckets of more than ``each`` bytes.

    A thing that every document has makes its bucket as many questions as there are chunks; parts keep them apart.
    """
    size = F.sum(F.octet_length("payload") + 64)
    many = written(asked.groupBy("b").agg(F.ceil(size / each).cast("long").alias("parts")).where("parts > 1"))
    part = F.pmod(F.xxhash64("g"), F.coalesce("parts", F.lit(1).cast("long")))
    return asked.join(many, "b", "left").withColumn("s", part).drop("parts"), many


def total_bytes(chunks: DataFrame) -> int:
    """Bytes of all chunks as they are stored (compressed), for the number of buckets."""
    return int(chunks.agg(F.sum(F.octet_length("body"))).first()[0] or 0)
