"""Where a search starts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathweave.automaton import Automaton
from pathweave.graph import PathGraph


def resolve(g: PathGraph, a: Automaton, adj: DataFrame, start, backward: bool = False) -> DataFrame:
    """(start): the constant, if it is a node; without one the nodes with an edge that the initial state takes, or all nodes
    if the empty word matches; or the nodes of a DataFrame (start)."""
    kind = g.nodes.schema["id"].dataType
    if isinstance(start, DataFrame):
        return start.select(F.col(start.columns[0]).cast(kind).alias("start")).distinct().join(g.nodes.withColumnRenamed("id", "start"), "start", "left_semi")
    if start is not None:
        return g.nodes.filter(F.col("id") == F.lit(start).cast(kind)).select(F.col("id").alias("start")).distinct()
    if a.accepts_empty():
        return g.nodes.select(F.col("id").alias("start")).distinct()
    first = {(s[0], s[1] ^ backward) for q, s, _ in a.delta if q == a.initial}
    hit = F.lit(False)
    for label, inverse in sorted(first):
        hit = hit | ((F.col("label") == label) & (F.col("inverse") == inverse))
    return adj.filter(hit).select(F.col("node").alias("start")).distinct()
