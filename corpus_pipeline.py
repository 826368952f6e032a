"""From raw documents to encoded ones, in stages that are written and read again.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; all but the last
return the columns of documents.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from temporal_patterns.llm import byte_bpe, jaccard_trie, line_dedup, mixing, quality
from temporal_patterns.llm.workspace import keep


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules and the n-gram model keep."""
    judged = quality.assess(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return judged.where("kept").select(docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of documents that share 80 % of their five-word shingles."""
    return jaccard_trie.keep_one(docs)


def repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without lines that stand earlier in the corpus; one that loses all its words goes."""
    cut = line_dedup.drop_repeated_lines(docs)
    return cut.where(r"n_removed = 0 or text rlike '[^ \\t-\\r]'").select(docs.columns)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix of sources to their target weights, as documents."""
    return mixing.mixed_texts(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with their token ids."""
    return byte_bpe.encode_documents(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES = [
    ("quality rules", quality_rules),
    ("n-gram Jaccard join", near_duplicates),
    ("substring dedup", repeated_lines),
    ("mixing sources", source_mix),
    ("byte-level BPE", encode),
]

#: Hashes and merges decide here that SQL has no functions for; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = keep(docs, f"stage-{k}")
    return docs
