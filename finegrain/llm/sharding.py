"""Shards by a keyed permutation of the global row numbers.

Rows are numbered 0..N-1 in the order of (doc_id, CRC-32 of the text, size); a balanced Feistel
network over the smallest even-width power of two that holds N, walked along its cycle until the
value is below N, permutes the numbers. Number p goes to shard ``p mod n_shards`` at slot
``p div n_shards``: shard and slot of any row can be computed from its number alone, shard sizes
differ by one row at most and slots have no gaps.

Only key, size and CRC travel; texts stay where they are unless ``shard`` is asked to keep them.
Null doc_ids come first in the numbering, null texts have size 1 and the CRC of no bytes; rows equal in
all three order columns get adjacent numbers in any order, which changes no count; a last order column, a hash of the place a row is read
from, spreads very many of them over tasks. An empty table gives no rows. Very long texts are read for size and CRC only, unless they are
kept. Columns of ``keep`` that have a name of this operator's own (doc_id, size, text_crc32, row_no, shard, slot) give way to it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from finegrain.llm.common import bounded, drop, free_prefix, n_bytes, text_or_empty, written

SEED = 20240229
ROUNDS = 6
OWN = ("doc_id", "size", "text_crc32", "row_no", "shard", "slot")
# Odd multipliers and offsets of the round function stay below 2**31, so that products of a
# half (below 2**31 too, up to 2**62 rows) fit a signed 64-bit integer, in SQL as well.
MULTIPLY, STEP = 1664525, 1013904223


def round_keys(seed: int = SEED, rounds: int = ROUNDS) -> list[int]:
    keys, x = [], seed % 2**31
    for _ in range(rounds):
        x = (x * MULTIPLY + STEP) % 2**31
        keys.append(x)
    return keys


def half_bits(n: int) -> int:
    """Bits of each half of the network over the least domain of even width that holds n values."""
    return max(1, ((max(n, 2) - 1).bit_length() + 1) // 2)


def permute(numbers: np.ndarray, n: int, seed: int = SEED, rounds: int = ROUNDS) -> np.ndarray:
    """The images of ``numbers`` (each in 0..n-1) under the permutation of 0..n-1."""
    bits = half_bits(n)
    mask = (1 << bits) - 1
    out = numbers.astype(np.int64).copy()
    walking = np.arange(len(out))
    while len(walking):
        left, right = out[walking] >> bits, out[walking] & mask
        for key in round_keys(seed, rounds):
            mixed = ((right ^ (key & mask)) * MULTIPLY + key) % (1 << 31)
            left, right = right, left ^ ((mixed >> 9) ^ mixed) & mask
        out[walking] = (left << bits) | right
        walking = walking[out[walking] >= n]
    return out


def numbered(rows: DataFrame, order: list[str]) -> DataFrame:
    """rows with ``row_no``, their 0-based place in the order of the columns ``order``.

    One range shuffle; what reaches the driver is one count for each partition.
    """
    spark = rows.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    own = free_prefix(rows.columns)
    at, of, first, tie = own + "at", own + "of", own + "before", own + "tie"
    key = F.monotonically_increasing_id()
    # Rows may be read again when the range's bounds are sampled, so a tie is broken by where a row is, not by chance.
    tied = rows.withColumn(tie, F.xxhash64(key)).repartitionByRange(n, *order, tie).sortWithinPartitions(*order).drop(tie)
    placed = written(tied.withColumn(at, key))
    part, row = F.shiftright(at, 33), F.col(at).bitwiseAND(2**33 - 1)
    counts = sorted(tuple(x) for x in placed.groupBy(part.alias("p")).count().collect())
    before, offsets = 0, []
    for p, c in counts:
        offsets.append((p, before))
        before += c
    starts = spark.createDataFrame(offsets or [(0, 0)], f"{of} long, {first} long")
    out = placed.withColumn(of, part).join(F.broadcast(starts), of)
    out = out.withColumn("row_no", row + F.col(first)).drop(at, of, first)
    out._total, out._table = before, placed
    return out


def shard(docs: DataFrame, n_shards: int = 16, seed: int = SEED, keep: tuple[str, ...] = ()) -> DataFrame:
    """Columns doc_id, size, text_crc32, row_no, shard, slot, and ``keep`` of docs (they travel too)."""
    rows = bounded(docs).select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (n_bytes() + 1).alias("size"),
        F.crc32(text_or_empty().cast("binary")).alias("text_crc32"),
        *(F.col(f"`{c}`") for c in keep if c.lower() not in OWN),
    )
    placed = numbered(rows, ["doc_id", "text_crc32", "size"])
    total = placed._total

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = permute(batch.column("row_no").to_numpy(zero_copy_only=False), total, seed)
            columns = [*batch.columns, pa.array((at % n_shards).astype(np.int32)), pa.array(at // n_shards)]
            yield pa.RecordBatch.from_arrays(columns, names=[*batch.schema.names, "shard", "slot"])

    schema = T.StructType(placed.schema.fields + [T.StructField("shard", T.IntegerType()), T.StructField("slot", T.LongType())])
    return placed.mapInArrow(deal, schema)


def write_shards(docs: DataFrame, path: str, n_shards: int = 16, seed: int = SEED) -> None:
    """docs as ``path/shard=s/`` with rows of each shard in slot order (several files a shard at scale)."""
    dealt = shard(docs, n_shards, seed, tuple(docs.columns))
    dealt.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


__all__ = ["drop", "half_bits", "numbered", "permute", "round_keys", "shard", "write_shards"]
