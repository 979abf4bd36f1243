"""The queries of the ten operators, each over whole tables with production parameters, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dagquotient.llm import bpe, decontaminate, lines, ngram_join, oracles, quality, shards, spotsigs, suffix, toxicity, urls
from dagquotient.llm.common import table


def _fold(modulus: int) -> Column:
    """crc32(doc_id as text) mod ``modulus``; null where doc_id is."""
    return F.crc32(F.col("doc_id").cast("string")) % modulus


def _judged(scored: DataFrame, held_out: Column, threshold: float) -> DataFrame:
    return scored.select("doc_id", F.coalesce(held_out, F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    forest = quality.train(docs, table(spark, sf_dir, "labels"), _fold(5) != 0)
    return _judged(quality.score(docs, forest), _fold(5) == 0, 0.3)


def op2_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return bpe.round_trip(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op3_suffix(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = suffix.dedup(table(spark, sf_dir, "documents", "doc_id", "text"), length=200, first="goes")
    removed = F.col("n_bytes") - F.octet_length("kept")
    return out.select("doc_id", "n_bytes", removed.cast("long").alias("n_removed"), F.size("starts").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


def op4_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge(table(spark, sf_dir, "pages", "page_id", "url"), [urls.rule(x) for x in RULES])


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, items = table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text")
    found = decontaminate.report(docs, items, window=10)
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "contaminated")


def op6_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.join(table(spark, sf_dir, "documents", "doc_id", "text"), n=3, percent=90)


def op7_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = lines.dedup(table(spark, sf_dir, "documents"), MIN_SITES)
    return out.select("doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    model = toxicity.train(docs, table(spark, sf_dir, "labels"), _fold(3) != 1)
    return _judged(toxicity.score(docs, model), _fold(3) == 1, 0.7)


def op9_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shards.assign(table(spark, sf_dir, "documents", "doc_id", "text"), SHARD_BYTES).select("doc_id", "bytes", "shard", "shard_bytes")


def op10_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spotsigs.edited(table(spark, sf_dir, "documents", "doc_id", "text"))


#: Fixed values of the contract: the explicit url rules.
RULES = ("allow com/", "block example.com/en/", "allow www.example.com/en/", "block net/es/", "block net/fr/")
#: The byte limit of a shard.
SHARD_BYTES = 16 * 2**20
#: Sites that a line must be on to count as boilerplate: lines of few sites are mostly short ones that meet by chance.
MIN_SITES = 8

LINES_SQL = f"""
WITH d AS (
  SELECT doc_id, source, unnest(string_split(coalesce(text, ''), chr(10))) AS raw,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos
  FROM documents),
b AS (
  SELECT trim(raw, ' ') AS line, min(doc_id) AS first_doc FROM d WHERE trim(raw, ' ') <> ''
  GROUP BY 1 HAVING count(DISTINCT source) >= {MIN_SITES}),
m AS (
  SELECT d.doc_id, d.raw, d.pos,
         b.line IS NOT NULL AND NOT (b.first_doc = d.doc_id AND row_number() OVER (PARTITION BY d.doc_id, trim(d.raw, ' ') ORDER BY d.pos) = 1) AS gone
  FROM d LEFT JOIN b ON trim(d.raw, ' ') = b.line)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_removed,
       sha256(coalesce(string_agg(raw, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS text_sha256
FROM m GROUP BY doc_id
"""

_WORDS_SQL = r"list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '')"

LEAKS_SQL = f"""
WITH d AS (SELECT doc_id, {_WORDS_SQL} AS w FROM documents),
i AS (SELECT DISTINCT item_id, {_WORDS_SQL} AS w FROM benchmark),
iw AS (
  SELECT DISTINCT item_id, least(10, len(w)) AS n, array_to_string(w[p : p + least(10, len(w)) - 1], ' ') AS g
  FROM (SELECT item_id, w, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS p FROM i WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM iw),
dw AS (
  SELECT doc_id, n, p, array_to_string(w[p : p + n - 1], ' ') AS g
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d, sizes WHERE len(w) >= n)),
h AS (SELECT doc_id, item_id, p, dw.n FROM dw JOIN iw ON dw.g = iw.g AND dw.n = iw.n),
c AS (SELECT doc_id, count(DISTINCT pos) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + n)) AS pos FROM h) GROUP BY doc_id),
s AS (SELECT doc_id, count(*) AS n_items, string_agg(x, ',' ORDER BY x) AS items FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS x FROM h) GROUP BY doc_id)
SELECT d.doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN c USING (doc_id) LEFT JOIN s USING (doc_id)
"""

SHARDS_SQL = f"""
WITH d AS (
  SELECT doc_id, strlen(coalesce(text, '')) AS bytes,
         ('0x' || substr(md5(concat_ws('|', doc_id::VARCHAR, text)), 1, 14))::BIGINT AS h FROM documents),
x AS (SELECT doc_id, bytes, depth, h >> (56 - depth)::INT AS prefix FROM d, range(0, 57) r(depth)),
s AS (SELECT depth, prefix, sum(bytes) AS total, count(*) AS n FROM x GROUP BY ALL),
f AS (
  SELECT x.doc_id, x.bytes, x.depth, x.prefix, total, row_number() OVER (PARTITION BY x.doc_id ORDER BY x.depth) AS rn
  FROM x JOIN s USING (depth, prefix) WHERE total <= {SHARD_BYTES} OR n = 1)
SELECT doc_id, bytes, depth || '-' || lower(to_hex(prefix)) || '-0' AS shard, total::BIGINT AS shard_bytes FROM f WHERE rn = 1
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {"op1_quality": op1_quality, "op2_bpe": op2_bpe, "op3_suffix": op3_suffix, "op4_urls": op4_urls, "op5_decontaminate": op5_decontaminate, "op6_ngram_join": op6_ngram_join, "op7_lines": op7_lines, "op8_toxicity": op8_toxicity, "op9_shards": op9_shards, "op10_fingerprints": op10_fingerprints}


def oracle_sql() -> dict[str, str]:
    return {
        "op3_suffix": oracles.repeats(),
        "op4_urls": oracles.url_verdicts([urls.rule(x) for x in RULES]),
        "op5_decontaminate": LEAKS_SQL,
        "op6_ngram_join": oracles.jaccard(3, 90),
        "op7_lines": LINES_SQL,
        "op9_shards": SHARDS_SQL,
        "op10_fingerprints": oracles.fingerprints(),
    }
