"""A corpus pipeline of five of the training-data operators, each over all that the one before kept.

STAGES lists (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet
and read again as the next one's docs. All but the last return the columns of documents, any further columns with them,
whatever their names.

Defined cases: null texts, empty ones and those without a letter have no language, so they go in the first stage; the later
stages, given such rows, keep them. A row without a doc_id is its own document and stays. Of rows that share a doc_id one
stays after near_duplicates; of equally near copies the one with the smallest doc_id. Null lang, source or n_chars change
nothing (rows with null lang aren't learnt from). Texts are worked on whole, however long. An empty table stays empty in
each stage; an empty benchmark contaminates nothing.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathweave.llm import common as C
from pathweave.llm import op1_decontaminate, op2_pii, op3_minhash, op6_packing, op8_language

#: Documents whose language is less sure than this go, as do those without a letter.
LEAST_SCORE = 0.4


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a recognised language; the classifier learns from this stage's input."""
    return op8_language.accepted(docs, op8_language.train(op8_language.learnable(docs)), LEAST_SCORE)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: five-word shingles, a similarity of 0.8 or more."""
    return op3_minhash.survivors(docs, percent=80)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no more of the benchmark than the rule allows."""
    return op1_decontaminate.clean(docs, C.table(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with personal data in their texts replaced by its kind."""
    return op2_pii.masked(docs).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents with their places in sequences."""
    return op6_packing.pack(docs)


STAGES = [
    ("language", language),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("personal_data", personal_data),
    ("packing", packing),
]

#: Trained models, components and packing are no SQL; the stages are tested against brute force (tests/llm/test_pipeline.py).
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = C.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = f"{C.shared_dir(spark)}/pipeline-{name}-{uuid.uuid4().hex}"
        made = stage(spark, docs, sf_dir)
        made.write.parquet(path)
        docs = spark.read.schema(made.schema).parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
