"""Near-duplicate documents by b-bit MinHash, confirmed on whole shingle sets.

1. A document's set is its distinct shingles of k words (with fewer words, the whole sequence). Documents with equal
   sets form a class, found by a hash of the set; one of them, with the least doc_id, stands for it.
2. ``BANDS * ROWS`` minima are drawn from each set. Band keys come from whole minima; a signature keeps the low ``BITS``
   bits of each minimum, packed. Two sets that are 0.8 alike share no band with a chance of (1 - 0.8**ROWS)**BANDS.
3. A band's bucket is never paired within itself. Each document has one first candidate: the least document of its
   buckets, a minimum by partial aggregation; a bucket that everything falls in costs one row a task.
4. A candidate's similarity is estimated from the bits in which its signatures agree, corrected for the 2**-BITS of
   unequal minima that agree by chance. Five standard errors below the threshold it is dropped; all others are
   confirmed on their whole sets. Confirmed links give components. Where the next step would have a document meet more than ``MEETINGS`` others
   on average, documents outside the largest component of one of their buckets first have up to ``TRIES`` - 1 further candidates, in random orders, from such a component.
5. Members of one bucket that are still in different components may be alike although neither is like the first
   candidate. In each bucket, the members outside its largest component meet all members, in blocks: signatures tell
   which of them have a possible partner in another component (each pair in the
   first bucket they share only); these members' whole sets meet in blocks again, and a block returns the links that join
   components, as many as it has rows at most. No pairs leave a block. Links inside a component change nothing, and a large group of
   copies with a few strangers costs its rows once, not their square.

A null text and a text without words have an empty set, link with nothing and are components of their own. Rows with one
doc_id are one document with the links of all of them. A null doc_id stands for no class: such a row has the component
of the documents with its very set, is kept if there are none, and has no other links. An empty table gives no rows. Ties have no
say: a component's least doc_id stands for it. Very long texts are taken whole, with about 30 bytes for each word while their set is made.
``near_duplicates`` reads doc_id and text only; ``keep_one_of_each`` keeps all columns of docs, whatever their names.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.llm.common import bounded, drop, free_name, written

WORDS = 5
ALIKE = (80, 100)  # 100 * intersection >= 80 * union
BANDS, ROWS, BITS = 32, 4, 4
TRIES, MEETINGS = 3, 4096
HUB_ROWS = 4_000_000  # edges of 16 bytes that one task may hold
BLOCK = 2048  # rows of a bucket whose signatures meet in one task, twice
SET_BLOCK = 512  # and whose texts do
PASS_BYTES = 1 << 20
BROADCAST_IDS = 1_000_000  # of 8 bytes each


def lower_table() -> bytes:
    return bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


class Shingler:
    """64-bit hashes of a text's distinct shingles, sorted."""

    def __init__(self, k: int):
        self.k, self.lower = k, lower_table()
        self.number: dict[bytes, int] = {}
        rng = np.random.default_rng(11)
        self.factors = rng.integers(0, 2**63, k, np.uint64) * np.uint64(2) + np.uint64(1)

    def word(self, w: bytes) -> int:
        known = self.number.get(w)
        if known is None:
            if len(self.number) >= 200_000:
                self.number.clear()
            known = self.number[w] = int.from_bytes(hashlib.blake2b(w, digest_size=8).digest(), "little")
        return known

    def shingles(self, text: str | None) -> np.ndarray:
        words = (text or "").encode("utf-8", "surrogatepass").translate(self.lower).split()
        if not words:
            return np.zeros(0, np.uint64)
        ids = np.fromiter(map(self.word, words), np.uint64, len(words))
        k = min(self.k, len(words))
        mixed = np.full(len(ids) - k + 1, k, np.uint64)
        for i in range(k):
            mixed = (mixed ^ (mixed >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9) + ids[i : len(ids) - k + 1 + i] * self.factors[i]
        return np.unique(mixed)


def permutations(n: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(29)
    return rng.integers(0, 2**32, n, np.uint32), rng.integers(0, 2**31, n, np.uint32) * np.uint32(2) + np.uint32(1)


def minima(sets: list[np.ndarray], n: int) -> np.ndarray:
    """n minima (32 bits each) of each non-empty set."""
    x = np.concatenate(sets)
    x = ((x ^ (x >> np.uint64(33))) * np.uint64(0xC2B2AE3D27D4EB4F) >> np.uint64(32)).astype(np.uint32)
    starts = np.cumsum([0, *map(len, sets)])[:-1]
    out = np.empty((len(sets), n), np.uint32)
    for i, (a, b) in enumerate(zip(*permutations(n), strict=True)):
        y = (x ^ a) * b
        y ^= y >> np.uint32(15)
        y *= np.uint32(0x2C1B3C6D)
        out[:, i] = np.minimum.reduceat(y, starts)
    return out


def band_keys(mins: np.ndarray) -> np.ndarray:
    """A 64-bit key of each band (with its number in it) for each set."""
    out = np.empty((len(mins), BANDS), np.uint64)
    for b in range(BANDS):
        key = np.full(len(mins), b + 1, np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        for r in range(ROWS):
            key = (key ^ mins[:, b * ROWS + r].astype(np.uint64)) * np.uint64(0x94D049BB133111EB)
            key ^= key >> np.uint64(29)
        out[:, b] = key
    return out.view(np.int64)


def packed_signature(mins: np.ndarray) -> np.ndarray:
    """The low BITS (4) bits of each minimum, two to a byte."""
    low = (mins & np.uint32(15)).astype(np.uint8)
    return low[:, ::2] | (low[:, 1::2] << 4)


def agreement(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """How many of the minima's bits agree wholly, for rows of packed signatures."""
    differ = a ^ b
    return ((differ & 15) == 0).sum(-1) + ((differ >> 4) == 0).sum(-1)


def estimate(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The similarity that the signatures' agreement shows, corrected for agreement by chance."""
    chance = 2.0**-BITS
    return (agreement(a, b) / (BANDS * ROWS) - chance) / (1 - chance)


def least_estimate(alike: tuple[int, int] = ALIKE) -> float:
    """The threshold less five standard errors of the estimate there."""
    j, chance = alike[0] / alike[1], 2.0**-BITS
    agree = j + (1 - j) * chance
    return j - 5 * float(np.sqrt(agree * (1 - agree) / (BANDS * ROWS))) / (1 - chance)


SIGNED = "doc_id long, text_hash long, n_shingles long, set_hash binary, bands array<long>, signature binary"


def signed(docs: DataFrame, k: int = WORDS) -> DataFrame:
    """doc_id, a hash of the text, size and hash of the set, band keys and packed signature (null for an empty set)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(k)
        for batch in batches:
            ids, held, room = [], [], 0

            def rows() -> pa.RecordBatch:
                mins = np.zeros((len(held), BANDS * ROWS), np.uint32)  # noqa: B023
                some = [i for i, s in enumerate(held) if len(s)]  # noqa: B023
                if some:
                    mins[some] = minima([held[i] for i in some], BANDS * ROWS)  # noqa: B023
                keys, signature = band_keys(mins), packed_signature(mins)
                full = [len(s) > 0 for s in held]  # noqa: B023
                columns = [
                    pa.array([i for i, _ in ids], pa.int64()),  # noqa: B023
                    pa.array([h for _, h in ids], pa.int64()),  # noqa: B023
                    pa.array([len(s) for s in held], pa.int64()),  # noqa: B023
                    pa.array([hashlib.blake2b(s.tobytes(), digest_size=16).digest() if f else None for s, f in zip(held, full)], pa.binary()),  # noqa: B023
                    pa.array([x if f else None for x, f in zip(keys, full)], pa.list_(pa.int64())),
                    pa.array([x.tobytes() if f else None for x, f in zip(signature, full)], pa.binary()),
                ]
                return pa.RecordBatch.from_arrays(columns, names=["doc_id", "text_hash", "n_shingles", "set_hash", "bands", "signature"])

            for i, h, cell in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                text = cell.as_py() or ""
                ids.append((i, h))
                held.append(shingler.shingles(text))
                room += len(text) + 100
                if room >= PASS_BYTES:
                    yield rows()
                    ids, held, room = [], [], 0
            if ids:
                yield rows()

    return bounded(docs).selectExpr("CAST(doc_id AS LONG) AS doc_id", "xxhash64(text) AS text_hash", "text").mapInArrow(run, SIGNED)


def passes_estimate(pairs: DataFrame, alike: tuple[int, int]) -> DataFrame:
    """pairs (with signatures sa, sb) whose estimate doesn't rule them out; signatures go."""
    least = least_estimate(alike)
    names = [c for c in pairs.columns if c not in ("sa", "sb")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                a, b = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(batch.num_rows, -1) for c in ("sa", "sb"))
                yield batch.select(names).filter(pa.array(estimate(a, b) >= least))

    return pairs.mapInArrow(run, pairs.select(names).schema)


def texts_of(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """id, text of the documents with these ids (read from a written table) that have a text.

    Up to BROADCAST_IDS ids are sent to the texts, which stay where they are; more of them meet the texts in a shuffle.
    """
    ids = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids
    texts = docs.select(F.col("doc_id").cast("long").alias("id"), "text").where("text IS NOT NULL AND id IS NOT NULL")
    return texts.join(ids, "id", "left_semi").dropDuplicates(["id", "text"])


def confirmed(pairs: DataFrame, docs: DataFrame, k: int, alike: tuple[int, int]) -> DataFrame:
    """The pairs a, b (written before) whose whole sets are alike; texts are fetched for the documents in pairs only."""
    texts = written(texts_of(docs, pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct()))
    both = pairs.join(texts.select(F.col("id").alias("a"), F.col("text").alias("ta")), "a")
    both = both.join(texts.select(F.col("id").alias("b"), F.col("text").alias("tb")), "b").select("a", "b", "ta", "tb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler, last = Shingler(k), (None, None)
        for batch in batches:
            good = []
            for a, b in zip(batch.column("ta"), batch.column("tb")):
                text = b.as_py()
                if text != last[0]:  # rows of one b mostly come together
                    last = (text, shingler.shingles(text))
                own = shingler.shingles(a.as_py())
                common = len(np.intersect1d(own, last[1], assume_unique=True))
                good.append(len(own) > 0 and alike[1] * common >= alike[0] * (len(own) + len(last[1]) - common))
            yield batch.select(["a", "b"]).filter(pa.array(good, pa.bool_()))

    return both.mapInArrow(run, "a long, b long").distinct()


def components(links: DataFrame) -> DataFrame:
    """id, component (least id reachable) of all ids in links a, b; ids without links have no row.

    Every round, each id's neighbours are linked to the least of them (larger ones first, then smaller ones), which
    halves long paths and keeps stars as they are, until nothing changes. All aggregation is partial: a hub costs one row a task. Where
    there are more than HUB_ROWS edges, aggregates are written before they are joined, so that Spark can split a hub's rows.
    """
    edges = written(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct())
    same, tables = False, []

    def kept(df: DataFrame) -> DataFrame:
        if n > HUB_ROWS:
            df = written(df)
            tables.append(df)
        return df

    while not same:
        n = edges.count()
        both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = kept(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")))
        large = kept(both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct())
        least = kept(large.groupBy("u").agg(F.min("v").alias("m")))
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        new = written(small.unionByName(least.select("u", F.col("m").alias("v"))).distinct())
        same = new.count() == n and new.join(edges, ["u", "v"], "left_anti").isEmpty()
        for old in (edges, *tables):
            drop(old)
        edges, tables = new, []
    tops = edges.select(F.col("v").alias("id")).distinct().withColumn("component", F.col("id"))
    return edges.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(tops)


def mixed_buckets(placed: DataFrame) -> DataFrame:
    """key, largest for the buckets of placed (key, id, component) that hold several components, the one with most members of which is largest."""
    shares = placed.groupBy("key", "component").agg(F.count("*").alias("n"))
    return shares.groupBy("key").agg(F.max(F.struct("n", "component"))["component"].alias("largest"), F.count("*").alias("c")).where("c > 1").select("key", "largest")


def block_pairs(rows: DataFrame, keys: DataFrame, block: int, columns: list[str]) -> DataFrame:
    """rows (with key, id, outside) dealt to pairs of blocks of their key: p of the members outside, q of all members.

    A row comes as a member of its block of all (``left`` false) and, if it is outside, of its block of those (``left``); in a
    bucket of one block (``alone``) it comes once. keys has a row for each row's key. Only buckets of several blocks are looked up, and each pair of blocks is dealt anew, so that a large bucket isn't one
    task's work.
    """
    blocks = lambda n: F.greatest(F.ceil(n / block), F.lit(1)).cast("long")
    large = keys.groupBy("key").agg(blocks(F.count("*")).alias("nq"), blocks(F.count_if("outside")).alias("np")).where("nq > 1")
    one = F.lit(1).cast("long")
    placed = rows.join(written(large), "key", "left").withColumns({"nq": F.coalesce("nq", one), "np": F.coalesce("np", one)})
    span = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.col(n) - 1))
    right = placed.select("key", span("np").alias("p"), F.pmod(F.xxhash64("id"), F.col("nq")).alias("q"), F.lit(False).alias("left"), (F.col("nq") == 1).alias("alone"), "id", "outside", *columns)
    left = placed.where("outside AND nq > 1").select("key", F.pmod(F.xxhash64("id"), F.col("np")).alias("p"), span("nq").alias("q"), F.lit(True).alias("left"), F.lit(False).alias("alone"), "id", "outside", *columns)
    return left.unionByName(right).repartition("key", "p", "q")


def meetings(table: pa.Table, label: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """Each row of the left block, and the rows of the right one that it meets: those with another label, each pair once."""
    ids, outside, is_left = (table.column(c).to_numpy() for c in ("id", "outside", "left"))
    alone = table.column("alone")[0].as_py()
    right = np.flatnonzero(~is_left)
    for i in np.flatnonzero(outside if alone else is_left):
        rest = right[(label[right] != label[i]) & (~outside[right] | (ids[right] > ids[i]))]
        if len(rest):
            yield i, rest


def with_partners(rows: DataFrame, keys: DataFrame, alike: tuple[int, int]) -> DataFrame:
    """key, id of the rows (key, id, component, outside, signature, bands) that have a possible partner of another component in their bucket."""
    least = least_estimate(alike)

    def run(table: pa.Table) -> pa.Table:
        ids, component = table.column("id").to_numpy(), table.column("component").to_numpy()
        signature = np.frombuffer(b"".join(table.column("signature").to_pylist()), np.uint8).reshape(len(ids), -1)
        bands = table.column("bands").combine_chunks().flatten().to_numpy().reshape(len(ids), -1)
        key = table.column("key")[0].as_py()
        found = np.zeros(len(ids), bool)
        for i, rest in meetings(table, component):
            rest = rest[estimate(signature[rest], signature[i][None, :]) >= least]
            if len(rest):
                first = (bands[rest] == bands[i]).argmax(1)  # they share this bucket at least
                rest = rest[bands[i][first] == key]
                found[rest] = True
                found[i] |= len(rest) > 0
        return pa.table({"key": table.column("key").filter(pa.array(found)), "id": pa.array(ids[found], pa.int64())})

    dealt = block_pairs(rows, keys, BLOCK, ["component", "signature", "bands"])
    return dealt.groupBy("key", "p", "q").applyInArrow(run, "key long, id long").distinct()


def joining_links(rows: DataFrame, keys: DataFrame, k: int, alike: tuple[int, int]) -> DataFrame:
    """Links a, b between components among the rows (key, id, component, outside, text) of each bucket, on whole sets."""

    def run(table: pa.Table) -> pa.Table:
        shingler = Shingler(k)
        sets = [shingler.shingles(t.as_py()) for t in table.column("text")]
        ids, label = table.column("id").to_numpy(), table.column("component").to_numpy().copy()
        size = np.array([len(x) for x in sets])
        start = np.cumsum(size) - size
        _, every = np.unique(np.concatenate(sets), return_inverse=True)
        flag = np.zeros(int(every.max()) + 1, bool)
        out = []
        for i, rest in meetings(table, label):
            own = every[start[i] : start[i] + size[i]]
            flag[own] = True
            if len(rest) * 8 < len(ids):
                common = np.array([int(flag[every[start[r] : start[r] + size[r]]].sum()) for r in rest])
            else:
                common = np.add.reduceat(flag[every], start, dtype=np.int64)[rest]
            flag[own] = False
            for r in rest[alike[1] * common >= alike[0] * (size[i] + size[rest] - common)]:
                if label[r] != label[i]:
                    out.append((ids[i], ids[r]))
                    label[label == label[r]] = label[i]
        pairs = np.array(out, np.int64).reshape(-1, 2)
        return pa.table({"a": pa.array(pairs[:, 0], pa.int64()), "b": pa.array(pairs[:, 1], pa.int64())})

    dealt = block_pairs(rows, keys, SET_BLOCK, ["component", "text"])
    return dealt.groupBy("key", "p", "q").applyInArrow(run, "a long, b long").distinct()


def near_duplicates(docs: DataFrame, k: int = WORDS, alike: tuple[int, int] = ALIKE) -> DataFrame:
    """doc_id, text_hash, n_shingles, component_id, kept for each row of docs."""
    rows = written(signed(docs, k))
    # Aggregates are written before they are joined with the rows they come from: such a join can split a hot key.
    classes = written(rows.where("set_hash IS NOT NULL AND doc_id IS NOT NULL").groupBy("set_hash").agg(F.min("doc_id").alias("id")))
    reps = rows.withColumnRenamed("doc_id", "id").join(classes, ["id", "set_hash"]).dropDuplicates(["id", "set_hash"])
    reps = written(reps.select("id", "bands", "signature"))
    banded = reps.select("id", F.explode("bands").alias("key"))
    several = written(banded.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key"))
    shared = written(banded.join(several, "key"))
    signs = reps.select("id", "signature")
    links, found, open_ = None, None, None
    for salt in range(TRIES):
        turn = F.struct((F.xxhash64("id", F.lit(salt)) if salt else F.lit(0).cast("long")).alias("turn"), "id")
        # Whom to try: at first all, then those outside their bucket's largest component, with one of its members.
        tried, offered = (shared, shared) if salt == 0 else (open_.where("outside"), open_.where("NOT outside"))
        first = written(offered.groupBy("key").agg(F.min(turn).alias("first")))
        firsts = tried.join(first, "key").groupBy(F.col("id").alias("a")).agg(F.min("first")["id"].alias("b")).where("a <> b")
        signed_pairs = firsts.join(signs.select(F.col("id").alias("a"), F.col("signature").alias("sa")), "a")
        signed_pairs = signed_pairs.join(signs.select(F.col("id").alias("b"), F.col("signature").alias("sb")), "b")
        new = confirmed(written(passes_estimate(signed_pairs, alike)), docs, k, alike)
        links = written(new if links is None else links.unionByName(new).distinct())
        found = components(links)
        placed = written(shared.join(found, "id", "left").withColumn("component", F.coalesce("component", "id")))
        mixed = written(mixed_buckets(placed))
        open_ = written(placed.join(mixed, "key").select("key", "id", "component", (F.col("component") != F.col("largest")).alias("outside")))
        sizes = open_.groupBy("key").agg(F.count_if("outside").alias("out"), F.count("*").alias("n"))
        rows_open, meetings_ = sizes.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum(F.col("out") * F.col("n")), F.lit(0))).first()
        if meetings_ <= MEETINGS * rows_open:
            break
    active = written(with_partners(open_.join(reps, "id"), open_, alike))
    if not active.isEmpty():
        texts = written(texts_of(docs, active.select("id").distinct()))
        active = written(active.join(open_, ["key", "id"]))
        more = written(joining_links(active.join(texts, "id"), active, k, alike))
        if not more.isEmpty():
            found = components(links.unionByName(more))
    member = rows.select("doc_id", "text_hash", "n_shingles", "set_hash").join(classes, "set_hash", "left").join(found, "id", "left")
    component = F.coalesce("component", "id", "doc_id")
    kept = F.when(F.col("doc_id").isNull(), F.col("id").isNull()).otherwise(F.col("doc_id") == component)
    return member.select("doc_id", "text_hash", "n_shingles", component.alias("component_id"), kept.alias("kept"))


def keep_one_of_each(docs: DataFrame, k: int = WORDS, alike: tuple[int, int] = ALIKE) -> DataFrame:
    """The rows of docs, unchanged, that are kept: one for each component (repeated rows go)."""
    stays = near_duplicates(docs, k, alike).where("kept").select("doc_id", "text_hash").distinct()
    own = free_name("own", docs.columns)
    named = docs.withColumn(own, F.xxhash64("text"))
    out = named.join(stays, named["doc_id"].cast("long").eqNullSafe(stays["doc_id"]) & (named[own] == stays["text_hash"]), "left_semi")
    return out.dropDuplicates(["doc_id", own]).select(*(F.col(f"`{c}`") for c in docs.columns))
