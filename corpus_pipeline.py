"""A corpus pipeline of five operators: quality, exact copies, near copies, mix, tokens.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept. All but the last return the
columns of documents. Labels come from ``labels`` beside the documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from biclique_spark.llm import bpe, exact_dedup, mixing, ngram_join, quality
from biclique_spark.llm.common import shrink_heaps, written

#: SQL can't express a fitted classifier; tests hold the stages against brute force.
ORACLE_SQL = None


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier doesn't reject. Null texts are scored as empty ones, rows with null ids like
    others, repeated rows alike; an empty table stays empty, and other columns may have any names."""
    return quality.keep(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, the row with the smallest id, nulls last; of rows with one id and equal texts one. Null texts are
    empty ones. Rows are judged one by one, so an id that repeats with another text loses nothing."""
    return exact_dedup.keep_first(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each component of near copies, the one with the smallest id, nulls last: shingles of five words,
    similarity of 0.8 or more. Rows without words all stay; rows are judged one by one where ids repeat or are null."""
    shrink_heaps(spark)
    return ngram_join.keep_one(docs, 5, 80)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them: 0 to 3 times, so that each source comes near its target. Rows without
    words are in no mix; rows that share an id share their count; a null source is a source of its own."""
    shrink_heaps(spark)
    return mixing.mixed_documents(docs)


def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids and decoded texts of what is left, as digests: a row for each row. Null texts have no tokens."""
    import public_tokenizers

    shrink_heaps(spark)
    return bpe.round_trip(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES = [
    ("quality classifier", keep_quality),
    ("exact dedup", drop_copies),
    ("n-gram Jaccard join", drop_near_copies),
    ("source mix", mix_sources),
    ("byte-level BPE", tokenize),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on ``documents``; tables between them cut the lineage."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        docs = docs if i == len(STAGES) - 1 else written(docs, "stage")
    return docs
