"""The training-data pipeline: five stages over documents, each written and read again.

Quality rules reject documents, near duplicates (five-word shingles, similarity 0.8) leave one of each group,
contaminated documents go, sources are mixed by the temperature weights of what is left, and the mixed rows get shards
and slots. All but the last stage return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from finegrain.llm import decontamination, minhash_dedup, quality_rules, sharding, source_mixing
from finegrain.llm.common import read, written
from finegrain.llm.queries import ORACLES

SHARDS = 16


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_rules.keep_good(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return minhash_dedup.keep_one_of_each(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontamination.keep_clean(docs, read(spark, sf_dir, "benchmark"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return source_mixing.mix(docs, details=False)


def shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return sharding.shard(docs, SHARDS, keep=tuple(docs.columns))


STAGES = [
    ("quality_rules", quality),
    ("minhash_near_dedup", near_duplicates),
    ("benchmark_decontamination", decontaminate),
    ("source_mixing", mix),
    ("sharding", shards),
]


def stage_sql(query: str, source: str) -> str:
    """A query's SQL over another table than documents."""
    return "(" + ORACLES[query].replace("FROM documents", f"FROM {source}") + ")"


#: The stages' SQL one after the other. Rows that the mixture repeats are alike in all columns, so it doesn't matter which gets which number.
ORACLE_SQL = f"""
WITH good AS (
  SELECT * FROM documents SEMI JOIN (SELECT doc_id FROM {stage_sql("op10_quality_rules", "documents")} WHERE kept) USING (doc_id)
), single AS (
  SELECT * FROM good SEMI JOIN (SELECT doc_id FROM {stage_sql("op4_minhash_dedup", "good").replace("least(len(w), 4)", f"least(len(w), {minhash_dedup.WORDS})")} WHERE kept) USING (doc_id)
), clean AS (
  SELECT * FROM single ANTI JOIN (SELECT doc_id FROM {stage_sql("op9_decontamination", "single")} WHERE contaminated) USING (doc_id)
), mixed AS (
  SELECT clean.*, copy FROM clean JOIN (SELECT doc_id, copy FROM {stage_sql("op5_source_mixing", "clean")}) USING (doc_id)
), dealt AS (
  SELECT doc_id, size, text_crc32, row_no, shard, slot FROM {stage_sql("op8_sharding", "mixed")}
), numbered AS (
  SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY row_no) - 1 AS copy FROM dealt
)
SELECT doc_id, size, text_crc32, text, lang, source, n_chars, row_no, shard, slot FROM numbered JOIN mixed USING (doc_id, copy)"""


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = written(docs)
    return docs
