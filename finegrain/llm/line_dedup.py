"""Cross-site boilerplate lines: a line on ``min_sites`` distinct sites or more goes everywhere.

1. Lines (trimmed of ASCII blanks; blank lines never count) are hashed to 96 bits, and a
   HyperLogLog sketch of the sites of each hash is built by partial aggregation; sketches merge, so a
   line that a third of all rows share costs one sketch a task.
2. A line with fewer occurrences than ``min_sites`` cannot reach it. Of the rest, an estimate outside
   ``min_sites * (1 +- margin)`` decides; within it, the distinct sites are counted exactly. margin is
   eight standard errors of the sketch and one site at least.
3. Boilerplate lines are taken from the documents they occur in; the kept lines stay in order. The hashes of these lines are
   written; up to ``BROADCAST_LINES`` of them are sent to where the lines are, and more are copied ``SALTS`` times, so that
   the places of a very common line meet it in as many tasks.

Only DataFrame functions. A null site is no site; null and empty texts keep nothing and count no
lines; the first of repeated rows has no privilege: all lose the line. A line that ties with ``min_sites`` is boilerplate. Documents
are matched again by doc_id and text hash, so repeated or null doc_ids are safe. An empty table gives no rows. Very long texts
are split as one array of lines within a row, of their own size. Columns of docs keep their names and values, but for those named n_lines, n_removed
or kept_text, which are replaced.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from finegrain.llm.common import free_prefix, text_or_empty, written

MIN_SITES = 5
LG_K = 9
BROADCAST_LINES = 1_000_000  # of 12 bytes each
SALTS = 16
BLANKS = " \t\r\x0b\x0c"


def trimmed(line: Column) -> Column:
    return F.btrim(line, F.lit(BLANKS))


def margin(lg_k: int = LG_K) -> float:
    """Eight standard errors of a HyperLogLog sketch with 2**lg_k registers."""
    return 8 * 1.04 / math.sqrt(2**lg_k)


def hashed_lines(docs: DataFrame, site: str) -> DataFrame:
    """h1, h2 (96 bits of hash of the trimmed line), site; a row for each line that isn't blank."""
    line = trimmed(F.col("_line"))
    rows = docs.select(F.col(site).cast("string").alias("site"), F.explode(F.split(text_or_empty(), "\n")).alias("_line"))
    return rows.where(F.length(line) > 0).select(F.xxhash64(line).alias("h1"), F.hash(line).alias("h2"), "site")


def boilerplate(docs: DataFrame, site: str = "source", min_sites: int = MIN_SITES, lg_k: int = LG_K) -> DataFrame:
    """h1, h2 of the lines on min_sites distinct sites or more."""
    lines = hashed_lines(docs, site)
    spread = (
        lines.groupBy("h1", "h2")
        .agg(F.count("site").alias("n"), F.hll_sketch_agg("site", F.lit(lg_k)).alias("sketch"))
        .where(F.col("n") >= min_sites)
        .select("h1", "h2", F.hll_sketch_estimate("sketch").alias("estimate"))
    )
    room = max(1.0, margin(lg_k) * min_sites)
    sure = spread.where(F.col("estimate") > min_sites + room).select("h1", "h2")
    near = spread.where(F.col("estimate").between(min_sites - room, min_sites + room)).select("h1", "h2")
    # Distinct sites first: a line that very many rows share costs the join a row for each site.
    exact = (
        lines.groupBy("h1", "h2", "site").agg(F.lit(1).alias("one"))
        .join(near, ["h1", "h2"], "left_semi")
        .groupBy("h1", "h2").agg(F.count("site").alias("sites"))
        .where(F.col("sites") >= min_sites).select("h1", "h2")
    )
    return sure.unionByName(exact)


def strip_boilerplate(docs: DataFrame, site: str = "source", min_sites: int = MIN_SITES, lg_k: int = LG_K) -> DataFrame:
    """docs' columns with n_lines, n_removed and kept_text (lines that aren't boilerplate, as they were)."""
    found = written(boilerplate(docs, site, min_sites, lg_k))
    own = free_prefix(docs.columns)
    line = trimmed(F.col("line"))
    places = docs.select(F.col("doc_id").cast("long").alias("id"), F.xxhash64(text_or_empty()).alias("th"), F.posexplode(F.split(text_or_empty(), "\n")).alias("pos", "line")).where(F.length(line) > 0)
    places = places.select("id", "th", "pos", F.xxhash64(line).alias("h1"), F.hash(line).alias("h2"))
    if found.count() <= BROADCAST_LINES:
        hit = places.join(F.broadcast(found), ["h1", "h2"], "left_semi")
    else:
        salted = found.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        hit = places.withColumn("salt", F.pmod(F.xxhash64("id", "th", "pos"), F.lit(SALTS)).cast("int")).join(salted, ["h1", "h2", "salt"], "left_semi")
    gone = hit.groupBy(F.col("id").alias(own + "gid"), F.col("th").alias(own + "gth")).agg(F.collect_set("pos").alias(own + "gone"))
    named = docs.select("*", F.col("doc_id").cast("long").alias(own + "id"), F.xxhash64(text_or_empty()).alias(own + "th"))
    joined = named.join(gone, F.col(own + "id").eqNullSafe(F.col(own + "gid")) & (F.col(own + "th") == F.col(own + "gth")), "left")
    keep = F.array_except(F.sequence(F.lit(0), F.size(own + "lines") - 1), F.coalesce(own + "gone", F.array().cast("array<int>")))
    out = joined.withColumn(own + "lines", F.split(text_or_empty(), "\n"))
    return out.select(
        *(F.col(f"`{c}`") for c in docs.columns if c not in ("n_lines", "n_removed", "kept_text")),
        F.size(F.filter(own + "lines", lambda x: F.length(trimmed(x)) > 0)).cast("long").alias("n_lines"),
        F.coalesce(F.size(own + "gone"), F.lit(0)).cast("long").alias("n_removed"),
        F.array_join(F.transform(keep, lambda i: F.get(own + "lines", i)), "\n").alias("kept_text"),
    )
