"""Corpus clean-up in five stages over ``documents``; each stage works on all that the one before kept.

In every stage null texts are empty texts, null ids are ids of their own, texts
are read whole however long, repeated rows are rows, an empty table gives an
empty one, and columns beyond those of ``documents`` are carried as they are.
Ties are settled by doc_id, then by a hash of the text.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from dupflow.llm import line_join, near_dedup, packing, quality, secrets
from dupflow.llm.common import materialize, table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Failing lines go, then documents that lose too much or fail the base rules; a null or empty text fails them."""
    return quality.clean_documents(docs)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of equal or nearly equal lines only the first stays; every document stays, rows equal in id and text lose the same lines."""
    return line_join.drop_repeated_lines(docs, share=line_join.SHARE, short=True)


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate class stays, the one of the least id; null ids stay only where a class has no other."""
    return near_dedup.keep_one(docs)


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Values of credentials that are not widely copied are blotted out; every document stays."""
    return secrets.redact(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces of all documents in sequences."""
    return packing.pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [
    ("quality rules", quality_rules),
    ("line dedup", line_dedup),
    ("MinHash near-dedup", near_dedup_stage),
    ("secret scans", secret_scan),
    ("packing", packing_stage),
]

#: Near-duplicate classes and token ids are beyond SQL; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written as Parquet and read again for the next."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
