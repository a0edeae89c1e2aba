"""Edge lists and triples from files, and answers to files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathweave.graph import PathGraph

EDGE_SCHEMA = "src string, label string, dst string, eid string"


def edge_list(spark: SparkSession, path: str, form: str = "parquet", schema: str = EDGE_SCHEMA, **options) -> PathGraph:
    """Edges from parquet, orc, csv or json; text forms are read with the stated schema, never by guessing."""
    reader = spark.read.options(**options)
    if form in ("csv", "json"):
        reader = reader.schema(schema)
    return PathGraph.of(reader.format(form).load(path))


def triples_text(spark: SparkSession, path: str, triple_is_edge: bool = False) -> PathGraph:
    """Lines "<s> <p> <o> ." (or quoted objects); other lines are left out."""
    part = lambda i: F.regexp_extract("value", r'^\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]|\\.)*)"[^\s.]*)\s*\.\s*$', i)
    t = spark.read.text(path).select(part(1).alias("s"), part(2).alias("p"), F.concat(part(3), part(4)).alias("o")).filter("p <> ''")
    return PathGraph.from_triples(t, triple_is_edge)


def write_edges(graph: PathGraph, path: str) -> None:
    graph.edges.repartition("label").write.mode("overwrite").partitionBy("label").parquet(path)


def read_edges(spark: SparkSession, path: str) -> PathGraph:
    return PathGraph.of(spark.read.parquet(path))


def write_answers(answers: DataFrame, path: str, form: str = "parquet", parts: int = 64) -> None:
    """Answers by a hash of their start; json writes paths as arrays."""
    out = answers.withColumn("part", F.pmod(F.xxhash64("start"), F.lit(parts)))
    out.write.mode("overwrite").partitionBy("part").format(form).save(path)
