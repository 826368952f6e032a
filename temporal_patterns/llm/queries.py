"""The registered queries of this subpackage: each operator over its whole table."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import byte_bpe, html_tree, jaccard_trie, line_dedup, lm_scoring, mixing, permutation_index, quality, suffix_doubling, token_counts


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def op1_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_documents(_read(spark, sf_dir, "documents"))


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents").select("doc_id", "text")
    return quality.assess(docs, _read(spark, sf_dir, "labels")).drop("text")


def op3_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_tree.extract(_read(spark, sf_dir, "pages").select("page_id", "url", "html")).drop("html")


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents").select("doc_id", "text")
    return token_counts.count_documents(docs, public_tokenizers.path("byte_bpe_50k.json")).drop("text")


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.drop_repeated_lines(_read(spark, sf_dir, "documents").select("doc_id", "text"))


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents").select("doc_id", "text")
    return byte_bpe.encode_documents(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, with_ids=False).drop("text")


def op7_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_trie.document_classes(_read(spark, sf_dir, "documents"), jaccard_trie.Likeness(size=3, num=90, den=100))


def op8_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = (_read(spark, sf_dir, t) for t in ("documents", "labels"))
    return lm_scoring.score(lm_scoring.fit(docs.select("doc_id", "text"), labels)).drop("text")


def op9_repeated_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents").select("doc_id", "text")
    return suffix_doubling.drop_repeated_bytes(docs, with_text=False).drop("spans")


def op10_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return permutation_index.nearest(_read(spark, sf_dir, "embeddings"), lambda i: F.pmod(i, F.lit(50)) == 0, 5)


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_mix, op2_quality, op3_extract, op4_token_counts, op5_line_dedup, op6_byte_bpe, op7_jaccard_join, op8_lm_scores, op9_repeated_bytes, op10_nearest, pipeline)
}

#: Lines dedup in SQL: units of five words or more, normalised; the first by (doc_id, place) stays.
ORACLES: dict[str, str] = {}
