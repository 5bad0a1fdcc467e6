"""A training corpus from raw documents: quality rules, near-duplicate removal, mixing, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written and read again as the next one's
`docs`. All but the last return the columns of `documents`. Counted as part of the subpackage `certgraph.llm`.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from certgraph.llm.mixing import Mix
from certgraph.llm.near_duplicates import distinct_documents
from certgraph.llm.packing import pack_documents
from certgraph.llm.quality import fitted_bands, labels_beside, passing_documents
from certgraph.plans.staging import Stages

#: Ids of one training sequence.
SEQUENCE_IDS, END_ID = 1024, 2


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep, with limits fitted on labelled ones; a null or empty text goes."""
    return passing_documents(docs, fitted_bands(docs, labels_beside(spark, sf_dir)))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group that shares at least 80 % of five-word shingles."""
    return distinct_documents(docs, width=5, percent=80)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeated or left out so that sources come near their target weights, in mixed order."""
    return Mix(docs).rows()


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each document stands in the training sequences."""
    return pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), capacity=SEQUENCE_IDS, end_id=END_ID)


STAGES = [
    ("quality rules", quality_stage),
    ("near duplicates", near_duplicate_stage),
    ("mixing", mixing_stage),
    ("packing", packing_stage),
]

#: The stages use compression, hashing and a tokenizer, which SQL cannot express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    st = Stages(spark, "pipeline")
    for name, stage in STAGES[:-1]:
        docs = st.keep(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
