"""The corpus pipeline: documents in, packed training sequences out.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the
columns of documents. What a stage decides takes effect: rejected documents go, one document
of each near-duplicate group stays, personal data is replaced in the text, and the mix holds
a row for each repetition of a document.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from bundlemv.llm import mixing, packing, pii, quality, simhash
from bundlemv.session import Scratch, discard, materialise, prepare_workers
from bundlemv.sources.tables import load_table

#: SQL has no form for the discriminant, the fingerprints and the tokenizer; tests hold each stage against a plain version.
ORACLE_SQL = None
#: What a stage keeps beside its result goes when a later stage begins on a written copy of it.
SCRATCH = Scratch()


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the discriminant, trained on all labels, takes for label 1."""
    prepare_workers(spark)
    with SCRATCH.step(docs):
        return quality.filter_quality(docs, load_table(spark, sf_dir, "labels"))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates (similarity 0.8 over shingles of five words): the one with the least id."""
    prepare_workers(spark)
    with SCRATCH.step(docs):
        return simhash.keep_one(docs, similarity=0.8, shingle=5)


def personal_data_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with personal data replaced."""
    prepare_workers(spark)
    with SCRATCH.step(docs):
        return pii.redact(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix by source: a row per repetition."""
    prepare_workers(spark)
    with SCRATCH.step(docs):
        return mixing.mixed_documents(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all rows and their places in sequences."""
    prepare_workers(spark)
    with SCRATCH.step(docs):
        return packing.pack_documents(docs)


STAGES = [
    ("quality", quality_stage),
    ("near-duplicates", near_duplicate_stage),
    ("personal-data", personal_data_stage),
    ("mixing", mixing_stage),
    ("packing", packing_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load_table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES[:-1]):
        last, docs = docs, materialise(stage(spark, docs, sf_dir), name)
        if i:
            discard(last)
    return STAGES[-1][1](spark, docs, sf_dir)
