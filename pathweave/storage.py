"""Tables in the folder that driver and executors share; what cuts lineage between rounds."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or a temporary folder where it is unset (on one machine only)."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        named = "file://" + tempfile.mkdtemp(prefix="pathweave-")
        sc.setCheckpointDir(named)
    return named.rstrip("/")


def settle(df: DataFrame, name: str) -> DataFrame:
    """df as a written table: computed once, with no lineage, and safe from the loss of executors."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bucketed(df: DataFrame, name: str, key: list[str], buckets: int) -> DataFrame:
    """df as a table of the shared folder, one file for each bucket of the key: a join on the key reads it where it lies."""
    table = f"{name}_{uuid.uuid4().hex}"
    path = f"{shared_dir(df.sparkSession)}/{table}"
    df.repartition(buckets, *key).write.bucketBy(buckets, *key).sortBy(*key).option("path", path).saveAsTable(table)
    return df.sparkSession.table(table)


class Levels:
    """An append-only table of the shared folder, one partition for each round, bucketed by a key: what a round adds is written
    once, and joins on the key read all rounds without moving them."""

    def __init__(self, first: DataFrame, name: str, key: list[str], buckets: int):
        self.spark, self.key, self.buckets, self.depth = first.sparkSession, key, buckets, -1
        self.table = f"{name}_{uuid.uuid4().hex}"
        self.path = f"{shared_dir(self.spark)}/{self.table}"
        self.add(first)

    def add(self, df: DataFrame) -> DataFrame:
        self.depth += 1
        rows = df.withColumn("round", F.lit(self.depth))
        rows.write.mode("append").partitionBy("round").bucketBy(self.buckets, *self.key).option("path", self.path).saveAsTable(self.table)
        return self.at(self.depth)

    def at(self, depth: int) -> DataFrame:
        return self.spark.table(self.table).filter(F.col("round") == depth).drop("round")

    def all(self) -> DataFrame:
        return self.spark.table(self.table).drop("round")
