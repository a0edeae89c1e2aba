"""The queries of the ten operators, each over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathweave.llm import common as C
from pathweave.llm import oracles
from pathweave.llm import op1_decontaminate, op2_pii, op3_minhash, op4_quality, op5_hosts, op6_packing, op7_tools, op8_language, op9_substring, op10_license


def op3_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op3_minhash.near_duplicates(C.table(spark, sf_dir, "documents"))


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    scanned = op1_decontaminate.scan(C.table(spark, sf_dir, "documents"), C.table(spark, sf_dir, "benchmark"))
    return op1_decontaminate.report(scanned).drop("spans")


def op2_pii_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op2_pii.personal_data(C.table(spark, sf_dir, "documents"))


def op6_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op6_packing.pack(C.table(spark, sf_dir, "documents"))


def op4_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op4_quality.judged(C.table(spark, sf_dir, "documents"))


def op5_host_reputation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A page's outcome is that of the label with its number: bad if of low quality or toxic."""
    bad = ((F.col("quality") == 0) | (F.col("toxic") == 1)).cast("int")
    labels = C.table(spark, sf_dir, "labels").select(F.col("doc_id").alias("page_id"), bad.alias("bad"))
    return op5_hosts.filtered(C.table(spark, sf_dir, "pages"), labels)


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op8_language.languages(C.table(spark, sf_dir, "documents"))


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op10_license.scan(C.table(spark, sf_dir, "documents"))


def op7_tool_linking(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The table has no tool messages: a user's turn counts as a call, the assistant's next turn as its result."""
    return op7_tools.linked(*op7_tools.from_dialogue(C.table(spark, sf_dir, "conversations")))


def op9_repeated_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op9_substring.repeated_passages(C.table(spark, sf_dir, "documents"))


QUERIES = {
    "op1_decontamination": op1_decontamination,
    "op2_pii_spans": op2_pii_spans,
    "op4_line_quality": op4_line_quality,
    "op5_host_reputation": op5_host_reputation,
    "op8_language_id": op8_language_id,
    "op7_tool_linking": op7_tool_linking,
    "op9_repeated_passages": op9_repeated_passages,
    "op10_license_scan": op10_license_scan,
    "op6_best_fit_packing": op6_best_fit_packing,
    "op3_minhash_dedup": op3_minhash_dedup,
}
#: Queries without SQL rest on trained models, packing, votes or components over hashes; they are tested against brute force.
SQL: dict[str, str] = oracles.SQL
