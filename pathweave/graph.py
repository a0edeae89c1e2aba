"""Edge-labelled directed multigraphs as two DataFrames."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathweave.storage import settle


class GraphError(ValueError):
    pass


@dataclass(frozen=True)
class PathGraph:
    """edges(src, label, dst, eid) and nodes(id). Node ids keep their own type (long or string), as do edge ids."""

    edges: DataFrame
    nodes: DataFrame
    #: Triples have no edges of their own: whether a triple may count as one, as TRAIL needs.
    triple_is_edge: bool = True
    kept: dict = field(default_factory=dict, compare=False, repr=False)

    # -- building ---------------------------------------------------------------
    @staticmethod
    def of(edges: DataFrame, nodes: DataFrame | None = None, triple_is_edge: bool = True) -> PathGraph:
        edges = edges.select("src", "label", "dst", "eid")
        if nodes is None:
            nodes = edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct()
        return PathGraph(edges, nodes.select("id"), triple_is_edge)

    @staticmethod
    def from_table(df: DataFrame, src, label, dst, eid, nodes: DataFrame | None = None) -> PathGraph:
        """Edges from any table: columns or expressions for ends, label and edge id; rows with a null end or label are left out."""
        col = lambda c: F.expr(c) if isinstance(c, str) else c
        e = df.select(col(src).alias("src"), col(label).alias("label"), col(dst).alias("dst"), col(eid).alias("eid"))
        return PathGraph.of(e.filter("src is not null and dst is not null and label is not null").distinct(), nodes)

    @staticmethod
    def from_triples(triples: DataFrame, triple_is_edge: bool = False) -> PathGraph:
        """(s, p, o) without edge ids; equal triples are one. The id is the triple's text, so it can't collide."""
        t = triples.select("s", "p", "o").distinct()
        eid = F.concat_ws(" ", F.col("s").cast("string"), "p", F.col("o").cast("string"))
        return PathGraph.of(t.select(F.col("s").alias("src"), F.col("p").alias("label"), F.col("o").alias("dst"), eid.alias("eid")), triple_is_edge=triple_is_edge)

    @staticmethod
    def from_sequence(df: DataFrame, order: list, node: str, label, eid, partition: list | None = None) -> PathGraph:
        """An edge from each row's node to the next row's, in the given order (within each partition if named). Without a
        partition the next row is found over range-partitioned runs, so no task holds the whole order."""
        label = F.expr(label) if isinstance(label, str) else label
        if partition:
            nxt = F.lead(node).over(Window.partitionBy(*partition).orderBy(*order))
            rows = df.select(F.col(node).alias("src"), label.alias("label"), nxt.alias("dst"), F.col(eid).alias("eid"))
        else:
            rows = next_in_order(df.select(F.col(node).alias("src"), label.alias("label"), F.col(eid).alias("eid"), *[F.col(o).alias(f"__o{i}") for i, o in enumerate(order)]), [f"__o{i}" for i in range(len(order))], "src", "dst")
        return PathGraph.of(rows.filter("dst is not null"), df.select(F.col(node).alias("id")).distinct())

    @staticmethod
    def from_sessions(df: DataFrame, node: str, ts: str, eid: str, group: str, gap: str = "30 minutes", label: str = "session") -> PathGraph:
        """An edge between consecutive nodes of one session of a group (a gap without rows ends a session)."""
        by = Window.partitionBy(group).orderBy(ts, eid)
        nxt = F.lead(F.struct(F.col(node).alias("n"), F.col(ts).alias("t"))).over(by)
        seconds = F.expr(f"cast(interval '{gap}' as interval day to second)")
        e = df.select(F.col(node).alias("src"), F.lit(label).alias("label"), F.when(nxt["t"] - F.col(ts) <= seconds, nxt["n"]).alias("dst"), F.col(eid).alias("eid"))
        return PathGraph.of(e.filter("dst is not null"))

    @staticmethod
    def from_asof(left: DataFrame, right: DataFrame, on: str, left_ts: str, right_ts: str, src: str, dst: str, eid: str, label: str = "asof", tolerance: str | None = None) -> PathGraph:
        """An edge from each left row to the last right row at or before it with the same key (within a tolerance)."""
        both = left.select(F.col(on).alias("k"), F.col(left_ts).alias("t"), F.lit(1).alias("side"), F.col(src).alias("src"), F.col(eid).alias("eid"), F.lit(None).cast(right.schema[dst].dataType).alias("d"))
        both = both.unionByName(right.select(F.col(on).alias("k"), F.col(right_ts).alias("t"), F.lit(0).alias("side"), F.lit(None).cast(left.schema[src].dataType).alias("src"), F.lit(None).cast(left.schema[eid].dataType).alias("eid"), F.col(dst).alias("d")))
        by = Window.partitionBy("k").orderBy("t", "side").rowsBetween(Window.unboundedPreceding, 0)
        seen = F.last(F.when(F.col("side") == 0, F.struct("d", "t")), ignorenulls=True).over(by)
        rows = both.withColumn("seen", seen).filter("side = 1 and seen is not null")
        if tolerance:
            rows = rows.filter(F.col("t") - F.col("seen.t") <= F.expr(f"cast(interval '{tolerance}' as interval day to second)"))
        return PathGraph.of(rows.select("src", F.lit(label).alias("label"), F.col("seen.d").alias("dst"), "eid"))

    # -- checks -----------------------------------------------------------------
    def validate(self) -> PathGraph:
        """Raises GraphError unless ends, labels and ids are there, ids are unique and ends are nodes."""
        e = self.edges
        missing = e.filter("src is null or dst is null or label is null or eid is null").limit(1).count()
        twice = e.groupBy("eid").count().filter("count > 1").limit(1).count()
        ends = e.select(F.col("src").alias("id")).union(e.select("dst")).distinct()
        loose = ends.join(self.nodes, "id", "left_anti").limit(1).count()
        for bad, what in ((missing, "an edge lacks an end, label or id"), (twice, "an edge id occurs twice"), (loose, "an edge ends at no node")):
            if bad:
                raise GraphError(what)
        return self

    # -- views ------------------------------------------------------------------
    def reverse(self) -> PathGraph:
        return PathGraph(self.edges.select(F.col("dst").alias("src"), "label", F.col("src").alias("dst"), "eid"), self.nodes, self.triple_is_edge)

    def two_way(self) -> DataFrame:
        """(node, label, inverse, next, eid): every edge seen from both ends."""
        e = self.edges
        return e.select(F.col("src").alias("node"), "label", F.lit(False).alias("inverse"), F.col("dst").alias("next"), "eid").unionByName(
            e.select(F.col("dst").alias("node"), "label", F.lit(True).alias("inverse"), F.col("src").alias("next"), "eid")
        )

    def subgraph(self, labels: list[str] | None = None, nodes: DataFrame | None = None, where: Column | None = None) -> PathGraph:
        e, n = self.edges, self.nodes
        if labels is not None:
            e = e.filter(F.col("label").isin(labels))
        if where is not None:
            e = e.filter(where)
        if nodes is not None:
            n = n.join(nodes.select("id"), "id", "left_semi")
            e = e.join(n.withColumnRenamed("id", "src"), "src", "left_semi").join(n.withColumnRenamed("id", "dst"), "dst", "left_semi")
        return PathGraph(e, n, self.triple_is_edge)

    def has(self, nodes: DataFrame) -> DataFrame:
        return nodes.join(self.nodes, "id", "left_semi")

    def missing(self, nodes: DataFrame) -> DataFrame:
        return nodes.join(self.nodes, "id", "left_anti")

    def degrees(self) -> DataFrame:
        """(id, degree): edges in and out; a loop counts twice, isolated nodes have 0."""
        ends = self.edges.select(F.col("src").alias("id")).unionAll(self.edges.select("dst"))
        return self.nodes.join(ends.groupBy("id").agg(F.count(F.lit(1)).alias("degree")), "id", "left").select("id", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"))

    def median_node(self):
        """The node in the middle by (degree, id), the lower of two. The degree comes from the histogram of degrees, the node
        from among those of that degree."""
        d = self.degrees()
        hist = sorted((r[0], r[1]) for r in d.groupBy("degree").count().collect())
        at, before = (sum(c for _, c in hist) - 1) // 2, 0
        for degree, c in hist:
            if at < before + c:
                return d.filter(F.col("degree") == degree).orderBy("id").limit(at - before + 1).agg(F.max("id")).first()[0]
            before += c
        return None

    def labels(self) -> DataFrame:
        """(label, edges) with a total (label null)."""
        return self.edges.rollup("label").agg(F.count(F.lit(1)).alias("edges"))

    def label_names(self, most: int = 10_000) -> list[str]:
        """The labels, for wildcards; a catalogue, not data."""
        rows = self.edges.select("label").distinct().orderBy("label").limit(most + 1).collect()
        if len(rows) > most:
            raise GraphError(f"more than {most} labels: name them in the expression")
        return [r[0] for r in rows]

    def dictionary_encode(self) -> tuple[PathGraph, DataFrame]:
        """The graph over long node ids, and the dictionary (id, code). Codes come from range partitions: each task numbers its own
        run after an offset made of counts by partition."""
        ranged = settle(self.nodes.distinct().repartitionByRange("id").sortWithinPartitions("id").select("id", F.spark_partition_id().alias("part")), "dictionary")
        local = ranged.withColumn("at", F.row_number().over(Window.partitionBy("part").orderBy("id")) - 1)
        sizes = {r["part"]: r["count"] for r in ranged.groupBy("part").count().collect()}
        offsets, total = {}, 0
        for p in sorted(sizes):
            offsets[p], total = total, total + sizes[p]
        codes = local.select("id", (F.get(F.array(*[F.lit(offsets.get(i, 0)) for i in range(max(offsets, default=0) + 1)]), F.col("part")) + F.col("at")).cast("long").alias("code"))
        codes = settle(codes, "dictionary")
        e = self.edges.join(codes.withColumnRenamed("id", "src").withColumnRenamed("code", "s"), "src").join(codes.withColumnRenamed("id", "dst").withColumnRenamed("code", "d"), "dst")
        return PathGraph(e.select(F.col("s").alias("src"), "label", F.col("d").alias("dst"), "eid"), codes.select(F.col("code").alias("id")), self.triple_is_edge), codes

    def packed(self) -> DataFrame:
        """Packed adjacency: (src, label, out) with all (dst, eid) of a label at a node in one row."""
        return self.edges.groupBy("src", "label").agg(F.array_sort(F.collect_list(F.struct("eid", "dst"))).alias("out"))

    def store(self, table: str, buckets: int = 64) -> None:
        """As a table partitioned by label, and bucketed and sorted by source, so that rounds join it without moving it."""
        self.edges.write.mode("overwrite").partitionBy("label").bucketBy(buckets, "src").sortBy("src").saveAsTable(table)

    def cached(self) -> PathGraph:
        """Edges settled once in the shared folder."""
        return PathGraph(settle(self.edges, "edges"), settle(self.nodes, "nodes"), self.triple_is_edge)


def next_in_order(df: DataFrame, order: list[str], value: str, out: str) -> DataFrame:
    """df without the order columns, with the value of the next row in the total order. Rows are range-partitioned; within a partition it is
    a window, and the first row of each partition reaches the last of the one before through a table of one row each."""
    parts = settle(df.repartitionByRange(*order).withColumn("__p", F.spark_partition_id()), "ordered")
    by = Window.partitionBy("__p").orderBy(*order)
    first = parts.groupBy("__p").agg(F.min_by(value, F.struct(*order)).alias("__first"))
    # One row for each partition: its next non-empty partition's first value.
    heads = first.withColumn("__head", F.lead("__first").over(Window.orderBy("__p"))).select("__p", "__head")
    rows = parts.withColumn("__next", F.lead(value).over(by)).withColumn("__last", F.lead(F.lit(1)).over(by).isNull())
    rows = rows.join(F.broadcast(heads), "__p")
    return rows.withColumn(out, F.when(F.col("__last"), F.col("__head")).otherwise(F.col("__next"))).drop("__p", "__head", "__next", "__last", *order)
