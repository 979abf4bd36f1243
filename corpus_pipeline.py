"""A training corpus in five stages: quality, line dedup, near duplicates, decontamination, tokens.

Each stage works on all that its predecessor kept, is written as Parquet to the shared folder and read again. The
first four keep the columns of ``documents`` (``n_chars`` follows the text); the last gives token ids.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagquotient.llm import bpe, decontaminate, lines, ngram_join, quality
from dagquotient.llm.common import cut, table
from dagquotient.llm.queries import MIN_SITES

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier doesn't reject: a score of 0.3 or more."""
    learn = F.crc32(F.col("doc_id").cast("string")) % 5 != 0
    forest = quality.train(docs, table(spark, sf_dir, "labels"), learn)
    return quality.score(docs.select(*COLUMNS), forest).where("score >= 0.3").select(*COLUMNS)


def without_boilerplate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without the lines that many sites print (their first copy stays)."""
    out = lines.dedup(docs.select(*COLUMNS), MIN_SITES)
    n_chars = F.when(F.col("n_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return out.withColumn("n_chars", n_chars).select(*COLUMNS)


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of the smallest id of each group of near copies: five-word shingles, similarity 0.8 or more."""
    return ngram_join.dedup(docs.select(*COLUMNS), n=5, percent=80)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no ten-word window of a benchmark item occurs."""
    return decontaminate.clean(docs.select(*COLUMNS), table(spark, sf_dir, "benchmark"), window=10)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids, ids_sha256, decoded_sha256: the ids of every text, and what they decode to."""
    import public_tokenizers

    return bpe.round_trip(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN, keep_ids=True)


Stage = Callable[[SparkSession, DataFrame, str], DataFrame]
STAGES: list[tuple[str, Stage]] = [
    ("quality", good),
    ("line_dedup", without_boilerplate),
    ("near_duplicates", without_near_copies),
    ("decontamination", without_benchmark),
    ("tokens", tokens),
]

#: A classifier and a tokenizer can't be put in SQL; tests hold every stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
