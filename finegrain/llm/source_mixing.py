"""Mixing sources to target weights by Poisson replication.

A source with weight w of the mixture and b bytes of text gets the rate
``w * total / b``: the mean number of times that each of its documents occurs. A document's
count is the inverse of the Poisson distribution function with that mean at a uniform number
hashed from (seed, doc_id, text), so that it is the same on each run and machine;
every document is then repeated that often and all rows are put in the order of another hash.

The table of rates has a row for each source and holds the distribution function from where it differs from 0 to where
it is 1 in double precision. It is broadcast; its size is the number of sources and the square roots of their rates, never
that of the documents. With more sources than ``SOURCES`` the rates stay a table that is joined (a hot source is split by Spark's adaptive
join), and there, or where the distribution functions have more than ``ENTRIES`` numbers together, Python draws row by row. Copies of
a row are made before the shuffle, from one row each, so a hot source needs no task of its own; the order key differs for all
copies. No table is refused: a source of a few bytes beside a large table gets the rate that its weight says. Only the argument
``epochs`` has a limit.

Null sources form a source of their own (reported as null), null and empty texts count as one byte
so that each source has a rate, repeated rows are drawn alike, ties in the order key are put in the order of doc_id and copy, an empty
table gives no rows. Very long texts travel whole, as one row for each copy. Columns of docs that have a name of this operator's own (rate,
copies, copy, shuffle_key) are replaced, unless ``details`` is off; any other names are kept.
"""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.functions import ArrowUDFType

from finegrain.llm.common import free_prefix, text_or_empty, written

SEED = "mix-1"
TEMPERATURE = 0.5
SOURCES = 100_000
ENTRIES = 4_000_000
EPOCHS = 500
SMALL_RATE = 500
CHUNK = 1 << 16
OWN = ("rate", "copies", "copy", "shuffle_key")


def uniform(*parts: Column) -> Column:
    """A number in (0, 1) from 52 bits of the MD5 of the parts."""
    digest = F.md5(F.concat_ws("|", *parts).cast("binary"))
    return (F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") + 0.5) / float(2**52)


def poisson_cdf(rate: float) -> list[float]:
    """P(count <= k) for k = 0, 1, ... until it doesn't change any more."""
    term, k, total, out = math.exp(-rate), 0, math.exp(-rate), []
    while True:
        out.append(total)
        k += 1
        term *= rate / k
        if k > rate and total + term == total:
            return out
        total += term


def poisson_reach(rate: float) -> int:
    """Farther from the mean than this, both tails together are below the double precision of 1."""
    return math.ceil(10 * math.sqrt(rate)) + 60


def poisson_window(rate: float) -> tuple[int, np.ndarray]:
    """The least count k that matters, and P(count <= k), P(count <= k + 1), ... until it is 1.

    Large rates, where exp(-rate) is no good start, go from the mode down and up by ratios of neighbours; the sum is made 1 afterwards.
    """
    if rate <= SMALL_RATE:
        return 0, np.array(poisson_cdf(rate))
    mode, reach = math.floor(rate), poisson_reach(rate)
    first = max(mode - reach, 0)
    down = np.cumprod(np.arange(mode, first, -1, dtype=float) / rate)[::-1]
    up = np.cumprod(rate / np.arange(mode + 1, mode + reach + 1, dtype=float))
    sums = np.cumsum(np.concatenate([down, [1.0], up]))
    return first, sums / sums[-1]


def poisson_draws(batches):
    """Counts for pairs of arrays of rates and uniform numbers."""
    import pyarrow as pa

    window = lru_cache(16)(poisson_window)
    for rates, us in batches:
        counts = []
        for rate, u in zip(rates.to_pylist(), us.to_pylist()):
            first, cdf = window(rate)
            counts.append(first + int(np.searchsorted(cdf, u, side="right")))
        yield pa.array(counts, pa.int64())


def _many_rates(sizes: DataFrame, weights: dict[str | None, float] | None, temperature: float, epochs: float) -> DataFrame:
    """The rates of any number of sources as a table; sums are in a fixed order, so that they are the same on each run."""
    sizes = sizes.withColumn("_source", F.col("_source").cast("string"))
    if weights is None:
        raw = sizes.withColumn("_raw", F.pow(F.col("_bytes").cast("double"), F.lit(float(temperature))))
    else:
        given = sizes.sparkSession.createDataFrame([(None if s is None else str(s), float(w)) for s, w in weights.items()], "_key string, _raw double")
        raw = sizes.join(given, F.col("_source").eqNullSafe(F.col("_key")), "left").withColumn("_raw", F.coalesce("_raw", F.lit(0.0))).drop("_key")
    raw = written(raw)
    buckets = max(1, raw.count() // 10_000)
    parts = raw.groupBy(F.pmod(F.xxhash64("_source"), F.lit(buckets)).alias("p")).agg(
        F.aggregate(F.sort_array(F.collect_list("_raw")), F.lit(0.0), lambda a, x: a + x).alias("w"), F.sum("_bytes").alias("b"))
    sums = parts.collect()
    whole, total = math.fsum(r["w"] for r in sums) or 1.0, sum(r["b"] for r in sums)
    share = F.col("_raw") / F.lit(whole)
    return raw.select("_source", "_bytes", share.alias("_share"), (F.lit(float(epochs)) * share * F.lit(float(total)) / F.col("_bytes")).alias("_rate"))


def source_rates(docs: DataFrame, weights: dict[str | None, float] | None = None, by: str = "source", temperature: float = TEMPERATURE, epochs: float = 1.0) -> DataFrame:
    """A row for each source: its bytes, share of the mixture and rate; for few sources also the distribution function.

    Without weights, shares are proportional to ``bytes ** temperature``. The output of the mixture has about
    ``epochs`` times the bytes of the input. An argument of more than 500 epochs of everything is refused as a mistake; rates aren't.
    """
    if epochs > EPOCHS:
        raise ValueError(f"{epochs} epochs of the whole table: {EPOCHS} at most")
    spark = docs.sparkSession
    sizes = docs.groupBy(F.col(by).alias("_source")).agg(F.sum(F.greatest(F.octet_length(text_or_empty()), F.lit(1)).cast("long")).alias("_bytes"))
    found = [(r[0], r[1]) for r in sizes.limit(SOURCES + 1).collect()]
    if len(found) > SOURCES:
        return _many_rates(sizes, weights, temperature, epochs)
    total = sum(b for _, b in found)
    raw = {s: (b**temperature if weights is None else float(weights.get(s, 0.0))) for s, b in found}
    whole = sum(raw[s] for s in sorted(raw, key=lambda s: (s is None, str(s)))) or 1.0
    rows = [(s, b, raw[s] / whole, epochs * raw[s] / whole * total / b) for s, b in found]
    schema = "_source string, _bytes long, _share double, _rate double"
    if sum(min(r[3], poisson_reach(r[3])) + poisson_reach(r[3]) for r in rows) > ENTRIES:
        return F.broadcast(spark.createDataFrame(rows, schema))
    tables = [(first, cdf.tolist()) for first, cdf in (poisson_window(r[3]) for r in rows)]
    return F.broadcast(spark.createDataFrame([r + t for r, t in zip(rows, tables)], schema + ", _first long, _cdf array<double>"))


def mix(docs: DataFrame, weights: dict[str | None, float] | None = None, by: str = "source", temperature: float = TEMPERATURE, epochs: float = 1.0, seed: str = SEED, shuffle: bool = True, details: bool = True) -> DataFrame:
    """docs' columns, rate, copies, copy (from 0) and shuffle_key, a row for each copy, in shuffled order.

    Without details docs' columns only, all as they were.
    """
    rates = source_rates(docs, weights, by, temperature, epochs)
    kept = docs.select(*(F.col(f"`{c}`") for c in docs.columns if not details or c not in OWN))
    own = free_prefix(kept.columns)
    col = lambda name: F.col(own + name)
    rates = rates.withColumnsRenamed({c: own + c[1:] for c in rates.columns})
    joined = kept.join(rates, F.col(f"`{by}`").cast("string").eqNullSafe(col("source")))
    draw = uniform(F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.md5(text_or_empty().cast("binary")))
    if own + "cdf" in rates.columns:
        # Spark evaluates the draw once for a row: the comparison is with a constant of the lambda.
        count = col("first") + F.size(F.filter(col("cdf"), lambda c: c <= col("u")))
    else:
        count = F.arrow_udf(poisson_draws, "long", functionType=ArrowUDFType.SCALAR_ITER)(col("rate"), col("u"))
    drawn = joined.withColumn(own + "u", draw).withColumn(own + "copies", count.cast("long")).where(col("copies") > 0)
    # In chunks, as a row of a tiny source can have more copies than one array should hold.
    chunked = drawn.withColumn(own + "chunk", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((col("copies") - 1) / CHUNK))))
    start = col("chunk") * CHUNK
    copied = chunked.withColumn(own + "copy", F.explode(F.sequence(start, F.least(start + CHUNK, col("copies")) - 1)))
    copied = copied.withColumn(own + "key", F.xxhash64(F.lit(seed), F.col("doc_id"), col("u"), col("copy")))
    rows = [F.col(f"`{c}`") for c in kept.columns]
    out = copied.select(*rows, col("rate"), col("copies"), col("copy"), col("key"))
    out = out.orderBy(col("key"), "doc_id", col("copy")) if shuffle else out
    more = [col("rate").alias("rate"), col("copies").alias("copies"), col("copy").alias("copy"), col("key").alias("shuffle_key")]
    return out.select(*rows, *(more if details else []))
