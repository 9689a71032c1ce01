"""The corpus pipeline: filter by quality, drop near copies, mask, mix, pack.

Each stage takes (spark, docs, sf_dir), works on all that its predecessor kept, and returns a
DataFrame that is written as Parquet and read again as the next stage's documents. A table without rows
gives one without rows at every stage; columns besides doc_id, text, source and n_chars pass unread.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from tilemul.llm import mixing, nearcopies, packing, pii, quality
from tilemul.llm.common import HINTED_ONLY, read
from tilemul.session import scratch, settings


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 2: documents that the classifier rejects go.

    Null and empty texts are scored like any other, rows without an id too; repeated rows stay or go together.
    """
    return quality.keep_good(docs, quality.fit(docs, read(spark, sf_dir, "labels")))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 9's task on five-word shingles at similarity 0.8: one document of each group of near copies stays.

    It is the one of smallest doc_id, null last, then of smallest hash of its text; rows are told apart by id and
    text. Texts without words, null ones included, are copies of each other; shorter texts are one shingle.
    """
    return nearcopies.keep_one(docs)


def mask_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 8: personal data is replaced by its kind.

    All rows stay; a null text stays null, and n_chars follows a text that changes.
    """
    with settings(spark, **HINTED_ONLY):
        return pii.masked(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 3: documents as often, and as far, as the shards of the mix draw them.

    Rows without words go, a null source is a source, and the last block of a source may be cut to its first words.
    """
    return mixing.mixed(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 5: pieces of documents with their token ids, in sequences.

    A null or empty text is a piece of the end id; repeated rows are pieces of their own.
    """
    return packing.pack(packing.pieces(docs))


STAGES = [
    ("quality", quality_filter),
    ("near_dedup", near_dedup),
    ("personal_data", mask_personal_data),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: SQL has neither the classifier nor the tokenizer; the tests run the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what lies between them is written in the shared folder."""
    folder = f"{scratch(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    docs = read(spark, sf_dir, "documents")
    for n, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if n == len(STAGES) - 1:
            return out
        out.write.parquet(f"{folder}/{n}-{name}")
        docs = spark.read.parquet(f"{folder}/{n}-{name}")
    return docs
