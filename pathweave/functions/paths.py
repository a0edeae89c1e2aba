"""Functions over path columns, for use after a query."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathweave.automaton import Automaton


def path_length(eids: Column | str) -> Column:
    return F.size(eids)


def path_start(nodes: Column | str) -> Column:
    return F.element_at(nodes, 1)


def path_end(nodes: Column | str) -> Column:
    return F.element_at(nodes, -1)


def _col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def is_trail(eids: Column | str) -> Column:
    """No edge twice."""
    return F.size(F.array_distinct(eids)) == F.size(eids)


def is_acyclic(nodes: Column | str) -> Column:
    """No node twice."""
    return F.size(F.array_distinct(nodes)) == F.size(nodes)


def is_simple(nodes: Column | str) -> Column:
    """No node twice, but that the last may be the first."""
    n = _col(nodes)
    closed = (F.size(n) > 1) & (F.element_at(n, 1) == F.element_at(n, -1))
    return F.when(closed, is_acyclic(F.slice(n, F.lit(1), F.greatest(F.size(n) - 1, F.lit(0))))).otherwise(is_acyclic(n))


def path_text(eids: Column | str, sep: str = ">") -> Column:
    return F.array_join(F.transform(eids, lambda x: x.cast("string")), sep)


def path_reverse(items: Column | str) -> Column:
    return F.reverse(items)


def path_concat(first: Column | str, second: Column | str, nodes: bool = False) -> Column:
    """Two paths where the first ends at the second's start; of nodes, the meeting one stays once."""
    b = _col(second)
    return F.concat(_col(first), F.slice(b, F.lit(2), F.greatest(F.size(b) - 1, F.lit(0))) if nodes else b)


def accepts(labels: Column | str, a: Automaton) -> Column:
    """Whether the word of labels is in the automaton's language; a deterministic one, as a fold over the array."""
    d = a if not _branches(a) else a.determinise().minimise()
    moves = {(q, s[0]): r for q, s, r in d.delta if not s[1]}
    if not moves:
        return F.when(F.size(labels) == 0, F.lit(d.initial in d.finals)).otherwise(False)
    table = F.create_map(*[F.lit(x) for (q, label), r in moves.items() for x in (f"{q} {label}", r)])
    end = F.aggregate(labels, F.lit(d.initial), lambda q, x: F.coalesce(F.element_at(table, F.concat_ws(" ", q.cast("string"), x)), F.lit(-1)))
    return end.isin(list(d.finals))


def _branches(a: Automaton) -> bool:
    return len({(q, s) for q, s, _ in a.delta}) < len(a.delta)


def unnest_path(paths: DataFrame) -> DataFrame:
    """A row for each edge of each path: start, end, pos (from 1), eid, from_node, to_node."""
    step = F.arrays_zip(F.col("eids").alias("e"), F.slice("nodes", F.lit(1), F.size("eids")).alias("a"), F.slice("nodes", F.lit(2), F.size("eids")).alias("b"))
    return paths.filter(F.size("eids") > 0).select("start", "end", F.posexplode(step).alias("p", "s")).select("start", "end", (F.col("p") + 1).alias("pos"), F.col("s")["e"].alias("eid"), F.col("s")["a"].alias("from_node"), F.col("s")["b"].alias("to_node"))


def path_labels(paths: DataFrame, edges: DataFrame) -> DataFrame:
    """paths with labels, the array of their edges' labels."""
    keyed = paths.withColumn("__p", F.xxhash64("start", "end", F.col("eids").cast("string"))).withColumn("__k", F.struct("start", "end", "eids"))
    steps = keyed.select("__k", F.posexplode("eids").alias("pos", "eid")).join(edges.select("eid", "label"), "eid")
    words = steps.groupBy("__k").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "label"))), lambda x: x["label"]).alias("labels"))
    return keyed.join(words, "__k", "left").select(*paths.columns, F.coalesce("labels", F.array().cast("array<string>")).alias("labels"))


def path_cost(paths: DataFrame, costs: DataFrame, value: str, eid: str = "eid") -> DataFrame:
    """paths with cost: the sum of an attribute of their edges. Each edge's attribute is looked up once for each use."""
    keyed = paths.withColumn("__k", F.struct("start", "end", "eids"))
    sums = keyed.select("__k", F.explode("eids").alias(eid)).join(costs.select(eid, value), eid).groupBy("__k").agg(F.sum(value).alias("cost"))
    return keyed.join(sums, "__k", "left").select(*paths.columns, F.coalesce("cost", F.lit(0.0)).alias("cost"))


def register_udtf(spark) -> None:
    """unnest_path as a table function of SQL: SELECT * FROM unnest_path(eids)."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="pos int, eid string")
    class UnnestPath:
        def eval(self, eids):
            for i, e in enumerate(eids or []):
                yield i + 1, str(e)

    spark.udtf.register("unnest_path", UnnestPath)
