"""Answers of a query."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


class Result:
    """start, end, length, nodes, eids (endpoints only: start, end)."""

    def __init__(self, df: DataFrame, plan=None, counts: dict | None = None):
        self.df, self.plan, self._counts = df, plan, counts or {}

    def metrics(self) -> dict[str, float]:
        """Rounds, product keys and predecessors looked at, largest frontier: what the search reports about itself."""
        return {k: float(v) for k, v in self._counts.items()}

    def grouped(self) -> DataFrame:
        """Delivered by ends: each pair's paths together, shortest first."""
        return self.df.repartition("start", "end").sortWithinPartitions("start", "end", "length", "eids")

    def stream(self, limit: int | None = None) -> Iterator:
        """Answers one at a time; partitions are computed as they are asked for."""
        for i, row in enumerate(self.df.toLocalIterator()):
            if limit is not None and i >= limit:
                return
            yield row

    def with_attributes(self, df: DataFrame, key: str, on: str = "end") -> DataFrame:
        """Answers with the attributes of their end (or start); the planner broadcasts a small table by its size."""
        return self.df.join(df.withColumnRenamed(key, on), on)

    def top(self, k: int, by: str = "length", groups: bool = False) -> DataFrame:
        order = Window.partitionBy("start", "end").orderBy(by) if groups else Window.partitionBy("start", "end").orderBy(by, "eids")
        rank = F.dense_rank() if groups else F.row_number()
        return self.df.withColumn("__r", rank.over(order)).filter(F.col("__r") <= k).drop("__r")

    def minus(self, other: Result) -> DataFrame:
        return self.df.exceptAll(other.df)

    def intersect(self, other: Result) -> DataFrame:
        return self.df.intersect(other.df)

    def length_cube(self, mode: str) -> DataFrame:
        """Paths by mode and length, with totals (null) and the grouping number."""
        d = self.df.withColumn("mode", F.lit(mode))
        return d.cube("mode", "length").agg(F.count(F.lit(1)).alias("paths"), F.grouping_id().cast("long").alias("grouping"))
