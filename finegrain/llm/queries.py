"""Thin queries over the whole intended tables, one for each operator, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from pyspark.sql import functions as F

from finegrain.llm import decontamination, language_id, lattice_lm, line_dedup, minhash_dedup, quality_rules, sharding, source_mixing, suffix_dedup, token_counts
from finegrain.llm.common import read

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


BLANKS = "chr(32)||chr(9)||chr(13)||chr(11)||chr(12)"


@query(f"""
WITH lines AS (
  SELECT source, trim(unnest(string_split(coalesce(text, ''), chr(10))), {BLANKS}) AS line FROM documents
), boilerplate AS (
  SELECT list(line) AS all_lines FROM (
    SELECT line FROM lines WHERE line <> '' GROUP BY line HAVING count(DISTINCT source) >= {line_dedup.MIN_SITES})
), docs AS (
  SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls, coalesce(all_lines, []) AS b FROM documents, boilerplate
)
SELECT doc_id,
  CAST(len(list_filter(ls, lambda x: trim(x, {BLANKS}) <> '')) AS BIGINT) AS n_lines,
  CAST(len(list_filter(ls, lambda x: list_contains(b, trim(x, {BLANKS})))) AS BIGINT) AS n_removed,
  sha256(coalesce(array_to_string(list_filter(ls, lambda x: NOT list_contains(b, trim(x, {BLANKS}))), chr(10)), '')) AS kept_sha256
FROM docs""")
def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    stripped = line_dedup.strip_boilerplate(read(spark, sf_dir, "documents"))
    return stripped.select("doc_id", "n_lines", "n_removed", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))


@query(f"""
WITH sizes AS (
  SELECT source, CAST(sum(greatest(strlen(coalesce(text, '')), 1)) AS DOUBLE) AS b FROM documents GROUP BY source
), rates AS (
  SELECT source, pow(b, {source_mixing.TEMPERATURE}) / (SELECT sum(pow(b, {source_mixing.TEMPERATURE}) ORDER BY source) FROM sizes)
    * (SELECT sum(b) FROM sizes) / b AS rate FROM sizes
), cdf AS (
  SELECT source, rate, sum(exp(k * ln(rate) - rate - lgamma(k + 1))) OVER (PARTITION BY source ORDER BY k) AS c
  FROM (SELECT source, rate, unnest(range(0, CAST(150 + (SELECT coalesce(max(rate) + 40 * sqrt(max(rate)), 0) FROM rates) AS BIGINT))) AS k FROM rates)
), draws AS (
  SELECT doc_id, source, text, (CAST('0x' || substr(md5('{source_mixing.SEED}|' || doc_id || '|' || md5(coalesce(text, ''))), 1, 13) AS BIGINT) + 0.5) / 4503599627370496.0 AS u
  FROM documents
), counts AS (
  SELECT d.doc_id, d.source, d.text, c.rate, count(*) FILTER (WHERE c.c <= d.u) AS copies
  FROM draws d JOIN cdf c ON d.source IS NOT DISTINCT FROM c.source GROUP BY ALL
)
SELECT doc_id, source, text, round(rate, 9) AS rate, copies, unnest(range(0, copies)) AS copy FROM counts""")
def op5_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = source_mixing.mix(read(spark, sf_dir, "documents"))
    return mixed.selectExpr("doc_id", "source", "text", "round(rate, 9) AS rate", "copies", "copy")


def crc_sql(text: str) -> str:
    """CRC-32 of a text's UTF-8 bytes, byte by byte with the usual table."""
    start = f"list_transform(range(1, strlen({text}) + 1), lambda p: CAST('0x' || substr(hex(encode({text})), 2 * p - 1, 2) AS BIGINT))"
    return f"xor(list_reduce({start}, lambda c, b: xor(c >> 8, crc_table[CAST(xor(c & 255, b) AS INTEGER) + 1]), 4294967295), 4294967295)"


def feistel_sql(half: int) -> str:
    """One pass of the network: CTE-free, the rounds nested as a reduction over the keys."""
    mask = (1 << half) - 1
    mixed = f"(((xor(s[2], k & {mask}) * {sharding.MULTIPLY}) + k) % 2147483648)"
    step = f"[s[2], xor(s[1], xor({mixed} >> 9, {mixed}) & {mask})]"
    keys = ", ".join(f"[CAST({k} AS BIGINT)]" for k in sharding.round_keys())
    step = step.replace("k & ", "r[1] & ").replace("+ k)", "+ r[1])")
    return f"list_reduce([{keys}], lambda s, r: {step}, [x >> {half}, x & {mask}])"


def shard_sql(n_shards: int = 16) -> str:
    """The number of rows decides the width of the halves; SQL has a branch for each width that the tables here can need."""
    branches = " ".join(f"WHEN {h} THEN (SELECT (o[1] << {h}) | o[2] FROM (SELECT {feistel_sql(h)} AS o))" for h in range(1, 12))
    return f"""
WITH RECURSIVE bits AS (
  SELECT n, c FROM (SELECT CAST(i AS BIGINT) AS n, CAST(i AS BIGINT) AS c FROM range(0, 256) t(i))
), steps AS (
  SELECT n, c, 0 AS k FROM bits UNION ALL SELECT n, CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END, k + 1 FROM steps WHERE k < 8
), tables AS (
  SELECT list(c ORDER BY n) AS crc_table FROM steps WHERE k = 8
), docs AS (
  SELECT doc_id, CAST(strlen(coalesce(text, '')) + 1 AS BIGINT) AS size, CASE WHEN coalesce(text, '') = '' THEN 0 ELSE {crc_sql("coalesce(text, '')")} END AS text_crc32 FROM documents, tables
), placed AS (
  SELECT *, row_number() OVER (ORDER BY doc_id NULLS FIRST, text_crc32, size) - 1 AS row_no, count(*) OVER () AS total FROM docs
), sized AS (
  SELECT *, CAST(greatest(1, ceil(ceil(log2(greatest(total, 2))) / 2)) AS INTEGER) AS half FROM placed
), walked AS (
  SELECT row_no, total, half, row_no AS x, FALSE AS moved FROM sized
  UNION ALL
  SELECT row_no, total, half, CAST(CASE half {branches} END AS BIGINT), TRUE FROM walked WHERE NOT moved OR x >= total
)
SELECT doc_id, size, text_crc32, 'rows' AS law, CAST(x % {n_shards} AS INTEGER) AS shard, x // {n_shards} AS slot, CAST(NULL AS INTEGER) AS grown_shard, row_no
FROM sized JOIN (SELECT row_no AS own_no, x FROM walked WHERE moved AND x < total) ON own_no = row_no"""


@query(shard_sql())
def op8_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    dealt = sharding.shard(read(spark, sf_dir, "documents"), n_shards=16)
    return dealt.selectExpr("doc_id", "size", "text_crc32", "'rows' AS law", "shard", "slot", "CAST(NULL AS INT) AS grown_shard", "row_no")


@query(rf"""
WITH items AS (
  SELECT CAST(item_id AS VARCHAR) AS item_id, list_filter(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM benchmark
), patterns AS (
  SELECT DISTINCT item_id, n, array_to_string(w[i:i + n - 1], ' ') AS s
  FROM (SELECT item_id, w, least(len(w), {decontamination.WINDOW}) AS n, unnest(range(1, len(w) - least(len(w), {decontamination.WINDOW}) + 2)) AS i FROM items WHERE len(w) > 0)
), docs AS (
  SELECT doc_id, list_filter(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents
), windows AS (
  SELECT doc_id, n, i, array_to_string(w[i:i + n - 1], ' ') AS s
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM docs, (SELECT DISTINCT n FROM patterns))
), found AS (
  SELECT doc_id, i, n, item_id FROM windows JOIN patterns USING (n, s)
), hits AS (
  SELECT doc_id, count(DISTINCT i + k) AS n_hit FROM (SELECT DISTINCT doc_id, i, n FROM found), range(0, {decontamination.WINDOW}) t(k) WHERE k < n GROUP BY doc_id
), named AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT doc_id, item_id FROM found) GROUP BY doc_id
)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(ids, '')) AS items_sha256,
  coalesce(n_hit, 0) > 0 AND {decontamination.NEAR} * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM docs LEFT JOIN hits USING (doc_id) LEFT JOIN named USING (doc_id)""")
def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontamination.find(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark"))
    ids = F.sha2(F.array_join("items", ",").cast("binary"), 256)
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), ids.alias("items_sha256"), "contaminated")


@query(r"""
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents
), lines AS (
  SELECT doc_id, count(*) AS n, count(DISTINCT l) AS m FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS l FROM d)
  WHERE regexp_matches(l, '[^\x20\x09-\x0D]') GROUP BY doc_id
), windows AS (
  SELECT doc_id, i, array_to_string(w[i:i + 4], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM d)
), twice AS (
  SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, s) AS c FROM windows) WHERE c > 1
), again AS (
  SELECT doc_id, count(DISTINCT i + k) AS n FROM twice, range(0, 5) t(k) GROUP BY doc_id
), m AS (
  SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, length(regexp_replace(t, '[\x20\x09-\x0D]+', '', 'g')) AS word_chars,
    length(t) - length(translate(t, '#*$%&|<>', '')) AS n_symbols, coalesce(l.n - l.m, 0) AS n_dup_lines, coalesce(l.n, 0) AS n_lines, coalesce(a.n, 0) AS n_repeat_words,
    length(t) - length(translate(t, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', '')) AS upper, len(list_filter(range(2, len(w) + 1), lambda i: w[i] = w[i - 1])) AS n_stutters, length(t) - length(translate(t, 'abcdefghijklmnopqrstuvwxyz', '')) AS lower
  FROM d LEFT JOIN lines l USING (doc_id) LEFT JOIN again a USING (doc_id)
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
  n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
  NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words OR 10 * n_symbols > n_words OR word_chars < 2 * n_words OR word_chars > 25 * n_words
    OR 2 * n_dup_lines > n_lines OR 4 * n_stutters > n_words OR upper > lower) AS kept
FROM m""")
def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.measured(read(spark, sf_dir, "documents"))


TOKENIZER = "byte_bpe_50k.json"


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


@query()
def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(read(spark, sf_dir, "documents"), tokenizer_path(TOKENIZER))


@query()
def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    model = language_id.train(docs.where(~language_id.held_out()))
    return language_id.predict(docs, model).withColumn("held_out", language_id.held_out()).select("doc_id", "held_out", "lang_pred", "score", "ambiguous")


@query(f"""
WITH docs AS (
  SELECT doc_id, hex(encode(coalesce(text, ''))) AS h, CAST(strlen(coalesce(text, '')) AS BIGINT) AS n FROM documents
), windows AS (
  SELECT doc_id, p, substr(h, CAST(2 * p + 1 AS BIGINT), {2 * suffix_dedup.LENGTH}) AS s FROM (SELECT doc_id, h, unnest(range(0, n - {suffix_dedup.LENGTH - 1})) AS p FROM docs WHERE n >= {suffix_dedup.LENGTH})
), firsts AS (
  SELECT hash(s) AS a, md5_number(s) AS b, min(doc_id) AS f FROM windows GROUP BY 1, 2 HAVING min(doc_id) <> max(doc_id)
), starts AS (
  SELECT doc_id, p FROM windows JOIN firsts ON a = hash(s) AND b = md5_number(s) WHERE f < doc_id
), marks AS (
  SELECT doc_id, p, sum(d) AS d FROM (SELECT doc_id, p, 1 AS d FROM starts UNION ALL SELECT doc_id, p + {suffix_dedup.LENGTH}, -1 FROM starts) GROUP BY 1, 2
), depth AS (
  SELECT doc_id, p, sum(d) OVER (PARTITION BY doc_id ORDER BY p) AS covered, lead(p) OVER (PARTITION BY doc_id ORDER BY p) AS upto FROM marks
), runs AS (
  SELECT doc_id, p, upto, covered > 0 AS gone, coalesce(lag(covered) OVER (PARTITION BY doc_id ORDER BY p) > 0, FALSE) AS before FROM depth
), edges AS (
  SELECT doc_id, sum(CASE WHEN gone THEN upto - p ELSE 0 END) AS removed, count(*) FILTER (WHERE gone AND NOT before) AS spans, list({{'p': p, 'gone': gone, 'upto': upto}} ORDER BY p) AS parts FROM runs GROUP BY doc_id
), kept AS (
  SELECT d.doc_id, n, coalesce(removed, 0) AS removed, coalesce(spans, 0) AS spans,
    CASE WHEN parts IS NULL THEN h ELSE substr(h, 1, CAST(2 * parts[1].p AS BIGINT)) || list_reduce(list_transform(parts, lambda x: CASE WHEN x.gone THEN '' ELSE substr(h, CAST(2 * x.p + 1 AS BIGINT), CAST(2 * (coalesce(x.upto, n) - x.p) AS BIGINT)) END), lambda a, b: a || b, '') END AS h
  FROM docs d LEFT JOIN edges e ON e.doc_id = d.doc_id
)
SELECT doc_id, n AS n_bytes, CAST(removed AS BIGINT) AS n_removed, CAST(spans AS BIGINT) AS n_spans, sha256(unhex(h)) AS kept_sha256 FROM kept""")
def op3_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = suffix_dedup.cut_repeats(read(spark, sf_dir, "documents"))
    removed = F.aggregate("spans", F.lit(0).cast("long"), lambda n, s: n + s["end"] - s["start"])
    return cut.select("doc_id", "n_bytes", removed.alias("n_removed"), F.size("spans").cast("long").alias("n_spans"), "kept_sha256")


@query("""
WITH RECURSIVE docs AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents
), shingles AS (
  SELECT DISTINCT doc_id, array_to_string(w[i:i + least(len(w), 4) - 1], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - least(len(w), 4) + 2)) AS i FROM docs WHERE len(w) > 0)
), sizes AS (
  SELECT doc_id, count(*) AS n FROM shingles GROUP BY doc_id
), links AS (
  SELECT p.a, p.b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS common FROM shingles x JOIN shingles y ON x.s = y.s AND x.doc_id <> y.doc_id GROUP BY 1, 2) p
  JOIN sizes m ON m.doc_id = a JOIN sizes n ON n.doc_id = b WHERE 100 * common >= 80 * (m.n + n.n - common)
), reach AS (
  SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT reach.a, links.b FROM reach JOIN links ON links.a = reach.b
)
SELECT d.doc_id, coalesce(n, 0) AS n_shingles, c AS component_id, d.doc_id = c AS kept
FROM documents d JOIN (SELECT a, min(b) AS c FROM reach GROUP BY a) ON a = d.doc_id LEFT JOIN sizes s ON s.doc_id = d.doc_id""")
def op4_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash_dedup.near_duplicates(read(spark, sf_dir, "documents"), k=4).select("doc_id", "n_shingles", "component_id", "kept")


LATTICE_VOCABULARY = "piece_bpe_32k.model"


@query()
def op6_lattice_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lattice_lm.scores(read(spark, sf_dir, "documents"), tokenizer_path(LATTICE_VOCABULARY))
