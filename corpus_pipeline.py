"""The corpus pipeline: quality rules, exact dedup, n-gram join, best-fit packing.

Each stage reads what the stage before it kept, as written to the shared folder; all but
the last give rows with the columns of ``documents``.

Defined results: documents with a null, empty or blank text fail the quality rules and go;
of rows that repeat, even with their id, one stays; an empty table gives no rows; columns
beside ``doc_id`` and ``text`` pass through, null or not, and are not packed; very long texts
are judged whole and cut only by packing.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from gapselect.llm.coding import default_vocabulary
from gapselect.llm.common import shared_dir
from gapselect.llm.exact_dedup import drop_copies
from gapselect.llm.ngram_join import one_of_each
from gapselect.llm.packing import pack
from gapselect.llm.quality import filter_quality


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return filter_quality(docs)


def keep_first_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_copies(docs)


def keep_one_of_similar(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Near copies: five words a shingle, similarity of 0.8 or more."""
    return one_of_each(docs, width=5, percent=80)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack(docs, default_vocabulary())


STAGES = [
    ("quality_rules", keep_quality),
    ("exact_dedup", keep_first_copies),
    ("ngram_jaccard_join", keep_one_of_similar),
    ("best_fit_packing", pack_sequences),
]

#: Token ids and bin packing are not expressible in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; stages but the last are written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = f"{shared_dir(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs.write.parquet(f"{folder}/{k}-{name}")
            docs = spark.read.parquet(f"{folder}/{k}-{name}")
    return docs
