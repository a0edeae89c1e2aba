"""One step of the search of graph times automaton; the product itself is never built."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pathweave.automaton import Automaton
from pathweave.graph import PathGraph
from pathweave.storage import bucketed, settle


def transitions(spark: SparkSession, a: Automaton, backward: bool = False) -> DataFrame:
    """(state, label, inverse, to): as many rows as the automaton has moves, so always broadcast. A search from the end walks
    every edge the other way round."""
    rows = [(q, s[0], s[1] ^ backward, r) for q, s, r in a.delta]
    return spark.createDataFrame(rows, "state int, label string, inverse boolean, to int")


def adjacency(g: PathGraph, a: Automaton, backward: bool = False) -> DataFrame:
    """(node, label, inverse, next, eid) of the labels and directions that the automaton has, settled once for a graph."""
    key = tuple(sorted({(s[0], s[1] ^ backward) for _, s, _ in a.delta}))
    if key not in g.kept:
        out = None
        for inverse in (False, True):
            labels = [label for label, i in key if i == inverse]
            if not labels:
                continue
            ends = ("dst", "src") if inverse else ("src", "dst")
            part = g.edges.filter(F.col("label").isin(labels)).select(F.col(ends[0]).alias("node"), "label", F.lit(inverse).alias("inverse"), F.col(ends[1]).alias("next"), "eid")
            out = part if out is None else out.unionByName(part)
        if out is None:
            e = g.edges.filter("false")
            out = e.select(F.col("src").alias("node"), "label", F.lit(False).alias("inverse"), F.col("dst").alias("next"), "eid")
        g.kept[key] = settle(out, "adjacency")
    return g.kept[key]


def expand(frontier: DataFrame, delta: DataFrame, adj: DataFrame) -> DataFrame:
    """frontier(node, state, ...) -> its rows for each matching edge, with to (state), next (node) and eid. The moves are broadcast
    (a few rows); whether the frontier is, or both sides are shuffled and split where skewed, is left to the adaptive planner."""
    moved = frontier.join(F.broadcast(delta), "state")
    return moved.join(adj, ["node", "label", "inverse"])


#: Parts of an even share of a bucket from which on a node's edges of one move are dealt over several buckets.
HUB = 0.5


@dataclass
class Stored:
    """An adjacency as (node, move, next, eid), bucketed by node and move. Where there are hubs (nodes with more edges of a move than
    HUB of a bucket's even share), it has a salt too, over which a hub's edges are dealt, and is bucketed by all three; hubs
    (node, move, salts) are at most buckets / HUB rows, so they may be broadcast."""

    edges: DataFrame
    hubs: DataFrame | None
    moves: dict

    def transitions(self, spark: SparkSession, a: Automaton, backward: bool) -> DataFrame:
        """(state, move, to): as many rows as the automaton has moves."""
        return spark.createDataFrame([(q, self.moves[s[0], s[1] ^ backward], r) for q, s, r in a.delta], "state int, move int, to int")

    def expand(self, frontier: DataFrame, delta: DataFrame) -> DataFrame:
        """frontier(node, state, ...) -> its rows for each matching edge, with to, next and eid. Only the frontier moves."""
        moved = frontier.join(F.broadcast(delta), "state")
        if self.hubs is None:
            return moved.join(self.edges, ["node", "move"])
        moved = moved.join(F.broadcast(self.hubs), ["node", "move"], "left").withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce("salts", F.lit(1)) - 1))).drop("salts")
        return moved.join(self.edges, ["node", "move", "salt"])

    def back(self, frontier: DataFrame, delta: DataFrame) -> DataFrame:
        """frontier(node, state) -> (prev, from): the product keys that step to it."""
        turned = delta.select(F.col("to").alias("state"), "move", F.col("state").alias("from"))
        return frontier.join(F.broadcast(turned), "state").join(self.edges.select(F.col("next").alias("node"), "move", F.col("node").alias("prev")), ["node", "move"]).select("prev", "from")


def stored(g: PathGraph, a: Automaton, backward: bool = False, buckets: int | None = None) -> Stored:
    """The adjacency of an automaton's labels and directions in bucketed form, written once for a graph."""
    names = sorted({(s[0], s[1] ^ backward) for _, s, _ in a.delta})
    spark = g.edges.sparkSession
    buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
    key = ("stored", tuple(names), buckets)
    if key not in g.kept:
        moves = {m: i for i, m in enumerate(names)}
        catalogue = spark.createDataFrame([(*m, i) for m, i in moves.items()], "label string, inverse boolean, move int")
        adj = adjacency(g, a, backward).join(F.broadcast(catalogue), ["label", "inverse"]).select("node", "move", "next", "eid")
        share = max(1.0, HUB * adj.count() / buckets)
        hubs = adj.groupBy("node", "move").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > max(share, 1000.0))
        hubs = settle(hubs.select("node", "move", F.ceil(F.col("n") / share).cast("int").alias("salts")), "hubs")
        if not hubs.limit(1).count():
            g.kept[key] = Stored(bucketed(adj, "adjacency", ["node", "move"], buckets), None, moves)
        else:
            salted = adj.join(F.broadcast(hubs), ["node", "move"], "left").withColumn("salt", F.pmod(F.xxhash64("eid"), F.coalesce("salts", F.lit(1))).cast("int"))
            g.kept[key] = Stored(bucketed(salted.select("node", "move", "salt", "next", "eid"), "adjacency", ["node", "move", "salt"], buckets), hubs, moves)
    return g.kept[key]


def lengthened(array: Column, item: Column, backward: bool) -> Column:
    return F.array_prepend(array, item) if backward else F.array_append(array, item)


def valid(restrictor: str, backward: bool = False) -> Column:
    """Whether a path row (start, node, eids, nodes) may take the edge (eid, next)."""
    if restrictor == "TRAIL":
        return ~F.array_contains("eids", F.col("eid"))
    fresh = ~F.array_contains("nodes", F.col("next"))
    if restrictor == "ACYCLIC":
        return fresh
    if restrictor == "SIMPLE":
        closed = (F.size("eids") > 0) & (F.col("node") == F.col("start"))
        return (fresh | (F.col("next") == F.col("start"))) & ~closed
    return F.lit(True)
