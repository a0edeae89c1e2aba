"""Paths from predecessor tables: backward joins, or count and unrank when only some are wanted."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathweave.storage import settle

KEY = ["start", "node", "state"]
EVERY = 6  # rounds between written tables


def all_paths(answers: dict[int, DataFrame], pred: dict[int, DataFrame], backward: bool, kinds: tuple[str, str]) -> DataFrame:
    """answers[depth](start, node, state), pred[depth](start, node, state, p_node, p_state, eid) -> start, end, length, nodes, eids:
    every path, built from its end; as many rows are joined in a round as paths are returned."""
    node, eid = kinds
    cur = None
    for d in range(max(answers, default=-1), -1, -1):
        if d in answers:
            fresh = answers[d].select("start", F.col("node").alias("end"), "node", "state", F.lit(d).alias("length"), F.array("node").cast(f"array<{node}>").alias("nodes"), F.array().cast(f"array<{eid}>").alias("eids"))
            cur = fresh if cur is None else cur.unionByName(fresh)
        if d == 0:
            break
        step = cur.join(pred[d], KEY)
        pre = (lambda a, x: F.array_append(a, x)) if backward else (lambda a, x: F.array_prepend(a, x))
        cur = step.select("start", "end", F.col("p_node").alias("node"), F.col("p_state").alias("state"), "length", pre(F.col("nodes"), F.col("p_node")).alias("nodes"), pre(F.col("eids"), F.col("eid")).alias("eids"))
        if d % EVERY == 0:
            cur = settle(cur, "paths")
    return cur.select("start", "end", "length", "nodes", "eids")


def some_paths(answers: dict[int, DataFrame], pred: dict[int, DataFrame], limit: int, backward: bool, kinds: tuple[str, str]) -> DataFrame:
    """Like all_paths, for at most limit paths, allotted to answers in the order of their ends. answers also have cnt (paths, never
    counted beyond the limit), pred p_cnt. A path is a number below its answer's share; each round it falls into the interval
    of one predecessor. No path beyond the limit is begun."""
    node, eid = kinds
    every = None
    for d, a in answers.items():
        a = a.select(*KEY, "cnt", F.lit(d).alias("length"))
        every = a if every is None else every.unionByName(a)
    # Each answer has a path, so that many answers suffice: a bounded table.
    first = every.orderBy("start", "node", "length", "state").limit(limit)
    before = F.coalesce(F.sum("cnt").over(Window.orderBy("start", "node", "length", "state").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    share = settle(first.withColumn("before", before).filter(F.col("before") < limit).withColumn("share", F.least(F.col("cnt"), limit - F.col("before"))), "shares")
    rows = share.withColumn("rank", F.explode(F.sequence(F.lit(0), (F.col("share") - 1).cast("int")))).withColumn("rank", F.col("rank").cast("long"))
    rows = rows.select("start", F.col("node").alias("end"), "node", "state", "length", "rank", F.array("node").cast(f"array<{node}>").alias("nodes"), F.array().cast(f"array<{eid}>").alias("eids"))
    top = max(answers, default=0)
    cur = rows.filter(F.col("length") == top)
    pre = (lambda a, x: F.array_append(a, x)) if backward else (lambda a, x: F.array_prepend(a, x))
    for d in range(top, 0, -1):
        by = Window.partitionBy(*KEY).orderBy("p_node", "p_state", "eid")
        lo = F.coalesce(F.sum("p_cnt").over(by.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        ranged = pred[d].withColumn("lo", lo).filter(F.col("lo") < limit)
        step = cur.join(ranged, KEY).filter((F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("lo") + F.col("p_cnt")))
        cur = step.select("start", "end", F.col("p_node").alias("node"), F.col("p_state").alias("state"), "length", (F.col("rank") - F.col("lo")).alias("rank"), pre(F.col("nodes"), F.col("p_node")).alias("nodes"), pre(F.col("eids"), F.col("eid")).alias("eids"))
        cur = cur.unionByName(rows.filter(F.col("length") == d - 1))
        if d % EVERY == 0:
            cur = settle(cur, "paths")
    return cur.select("start", "end", "length", "nodes", "eids")

