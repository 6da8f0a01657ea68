"""A training corpus in five stages over ``documents``: language, near duplicates, personal
data, source mix, packing.

Each stage gets the documents that its predecessor left, as Parquet, and returns documents of
the same columns; the last returns the packed pieces. Nulls in any column are allowed, rows
may repeat, and an empty table passes through."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from recblock.llm import language_id, minhash_join, packing, pii, source_mix, textkernel
from recblock.session import checkpoint_root

#: No SQL: a learned model, a similarity join and a tokenizer decide.
ORACLE_SQL = None
#: Similarity of near duplicates in percent.
NEAR_PERCENT = 80


def identified_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no language can be found (no letter, or no text) go. The model judges
    whole rows where they stand, so no row moves."""
    shared = spark.sparkContext.broadcast(language_id.train(docs.select("doc_id", "text", "lang")))  # of bounded size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            for part in textkernel.parts(batch, "text"):
                yield part.filter(pa.array([name != language_id.UNSEEN for name in model.judge(part.column("text"))[0]], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def without_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group stays, of least id; see the operator for ids that repeat or are null."""
    return minhash_join.without_near_duplicates(docs, NEAR_PERCENT)


def masked_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every span of personal data is replaced by its kind in brackets."""
    return pii.masked(docs)


def mixed_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows as often as the mix takes them."""
    return source_mix.mixed_documents(docs)


def packed_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per piece with its sequence and place."""
    return packing.pack_documents(docs)


STAGES = [
    ("language_id", identified_language),
    ("near_dedup", without_near_duplicates),
    ("personal_data", masked_personal_data),
    ("source_mix", mixed_sources),
    ("packing", packed_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what lies between them is written to the shared folder."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = f"{checkpoint_root(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs.write.parquet(f"{folder}/{name}")
            docs = spark.read.parquet(f"{folder}/{name}")
    return docs
