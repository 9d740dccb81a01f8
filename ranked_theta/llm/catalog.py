"""Registered queries of the training-data operators and their DuckDB oracles."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from . import decontaminate, embeddings, lengths, mixing, quality, repeats, secrets, shinglejoin, tokenids, warc


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mix of all documents: weights 3, 1, 2 in turn, 150% of all words, two epochs at most."""
    return mixing.mix_report(_table(spark, sf_dir, "documents"), weights=(3, 1, 2), share=1.5, max_epochs=2.0)


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encoded lengths of all texts in the lower-case word tokenizer, with totals at every context limit."""
    return lengths.count_report(_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), end_id=1)


def op3_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents whose sets of five-word shingles have a Jaccard similarity of 0.75 or more."""
    return shinglejoin.join_report(_table(spark, sf_dir, "documents"), percent=75)


def op4_warc_archives(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages written as Zstandard archives and read back."""
    return warc.archive_report(_table(spark, sf_dir, "pages"), min_bytes=0)


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Secrets in all texts, with structurally confirmed keys and tokens."""
    return secrets.scan(_table(spark, sf_dir, "documents"))


def op6_embedding_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near-duplicate vectors under equal labels at cosine 0.98."""
    return embeddings.near_duplicates(_table(spark, sf_dir, "embeddings"), threshold=0.98)


def op7_repeated_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All texts without the bytes of any 400-byte string that occurs twice."""
    return repeats.remove(_table(spark, sf_dir, "documents"), length=400, texts=True)


def op8_benchmark_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Benchmark items of which a document holds three quarters of the five-word shingles."""
    return decontaminate.leaks(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"), threshold=0.75)


def op9_quality_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality scores of all texts, learnt from at most 20,000 labelled rows."""
    return quality.score_report(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"), train_rows=20_000)


def op10_token_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids of all texts in the lower-case word tokenizer, written as segments and read back."""
    return tokenids.token_report(_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), end_id=1)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_mix_sources, op2_token_counts, op3_jaccard_join, op4_warc_archives, op5_secret_scan, op6_embedding_duplicates, op7_repeated_strings, op8_benchmark_leaks, op9_quality_scores, op10_token_ids)}


def oracle_sql() -> dict[str, str]:
    return {"op1_mix_sources": mixing.ORACLE, "op3_jaccard_join": shinglejoin.ORACLE, "op4_warc_archives": warc.ORACLE, "op6_embedding_duplicates": embeddings.ORACLE, "op8_benchmark_leaks": decontaminate.ORACLE}
