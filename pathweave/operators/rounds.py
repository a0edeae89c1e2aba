"""Searches as rounds of joins: each round takes one step of the product from the whole frontier, for all starts at once.

The adjacency is bucketed by node and move, the visited keys by (start, node, state), both in as many buckets as a shuffle has
partitions: a round moves its frontier and its candidates only, and reads edges and visited keys where they lie. What a round
adds is written once to the shared folder; the driver reads counts only."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathweave.automaton import Automaton
from pathweave.graph import PathGraph
from pathweave.modes import PathMode
from pathweave.operators import condensed, enumeration, product
from pathweave.storage import Levels, settle

KEY = ["start", "node", "state"]


class PathTimeout(RuntimeError):
    """A search took longer than it was allowed to; its answers are not complete, so none are handed out."""


@dataclass
class Rounds:
    graph: PathGraph
    automaton: Automaton
    seeds: DataFrame
    backward: bool = False
    #: Keep only answers whose other end is this constant.
    target: object = None
    max_length: int | None = None
    limit: int | None = None
    timeout_s: float | None = None
    metrics: dict = field(default_factory=lambda: {"rounds": 0, "visited_rows": 0, "pred_rows": 0, "peak_frontier": 0})

    def __post_init__(self):
        g = self.graph
        self.spark = g.edges.sparkSession
        self.began = time.monotonic()
        self.buckets = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        self.adj = product.stored(g, self.automaton, self.backward, self.buckets)
        self.delta = self.adj.transitions(self.spark, self.automaton, self.backward)
        self.node, self.eid = g.nodes.schema["id"].dataType.simpleString(), g.edges.schema["eid"].dataType.simpleString()

    # -- shared -----------------------------------------------------------------
    def first(self) -> DataFrame:
        empty, one = F.array().cast(f"array<{self.eid}>"), F.array("start").cast(f"array<{self.node}>")
        return self.seeds.select("start", F.col("start").alias("node"), F.lit(self.automaton.initial).alias("state"), empty.alias("eids"), one.alias("nodes"))

    def final(self, df: DataFrame) -> DataFrame:
        df = df.filter(F.col("state").isin(list(self.automaton.finals)))
        return df if self.target is None else df.filter(F.col("node") == F.lit(self.target).cast(self.node))

    def step(self, frontier: DataFrame) -> DataFrame:
        """Path rows one edge on."""
        e = self.adj.expand(frontier, self.delta)
        long = lambda a, x: product.lengthened(F.col(a), F.col(x), self.backward)
        return e.select("start", F.col("next").alias("node"), F.col("to").alias("state"), long("eids", "eid").alias("eids"), long("nodes", "next").alias("nodes"))

    def levels(self, first: DataFrame, name: str, key: list[str]) -> tuple[Levels, DataFrame, int]:
        table = Levels(first, name, key, self.buckets)
        return table, *self.counted(table.at(0))

    def counted(self, df: DataFrame) -> tuple[DataFrame, int]:
        """A written frontier and its rows."""
        n = df.count()
        self.metrics["rounds"] += 1
        self.metrics["visited_rows"] += n
        self.metrics["peak_frontier"] = max(self.metrics["peak_frontier"], n)
        self.check()
        return df, n

    def check(self) -> None:
        if self.timeout_s is not None and time.monotonic() - self.began >= self.timeout_s:
            raise PathTimeout(f"more than {self.timeout_s} s")

    def ended(self, depth: int, n: int) -> bool:
        return n == 0 or self.max_length is not None and depth >= self.max_length

    def out(self, answers: DataFrame) -> DataFrame:
        """Answers in the query's own direction."""
        ends = (F.col("node").alias("start"), F.col("start").alias("end")) if self.backward else (F.col("start"), F.col("node").alias("end"))
        return answers.select(*ends, F.size("eids").alias("length"), "nodes", "eids")

    def turned(self, paths: DataFrame) -> DataFrame:
        if not self.backward:
            return paths
        return paths.select(F.col("end").alias("start"), F.col("start").alias("end"), "length", "nodes", "eids")

    # -- endpoints --------------------------------------------------------------
    def endpoints(self) -> DataFrame:
        """(start, end): keys only, no paths."""
        seen, frontier, n = self.levels(self.first().select(*KEY), "reach", KEY)
        depth = 0
        while not self.ended(depth, n):
            new = self.adj.expand(frontier, self.delta).select("start", F.col("next").alias("node"), F.col("to").alias("state")).distinct()
            frontier, n = self.counted(seen.add(new.join(seen.all(), KEY, "left_anti")))
            depth += 1
        ends = self.final(seen.all()).select("start", F.col("node").alias("end")).distinct()
        return ends.select(F.col("end").alias("start"), F.col("start").alias("end")) if self.backward else ends

    def endpoints_by_class(self) -> DataFrame:
        """(start, end) of an expression of bounded length for many starts: rounds without pairs, from its end."""
        out = condensed.bounded(self.adj, self.automaton, self.seeds, self.backward, self.node)
        return out.select(F.col("end").alias("start"), F.col("start").alias("end")) if self.backward else out

    def endpoints_by_mask(self) -> DataFrame:
        """(start, end) by bit masks. Where the product is small enough for a worker, of the ends of each of its strong components.
        Else with 64 starts in a mask for each product node: visited is up to 64 times smaller. Starts are numbered by
        (block, bit) over range partitions."""
        if self.max_length is None:
            found = condensed.within(self.adj, self.automaton, self.seeds, self.backward, self.target, self.node)
            if found is not None:
                return found.select(F.col("end").alias("start"), F.col("start").alias("end")) if self.backward else found
        ranged = settle(self.seeds.repartitionByRange("start").sortWithinPartitions("start").select("start", F.spark_partition_id().alias("part")), "mask-starts")
        at = F.row_number().over(Window.partitionBy("part").orderBy("start")) - 1
        names = settle(ranged.withColumn("at", at).select("start", F.concat_ws(":", "part", F.floor(F.col("at") / 64)).alias("block"), (F.col("at") % 64).cast("int").alias("bit")), "mask-names")
        key = ["block", "node", "state"]
        mask = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("bit"))
        seen, frontier, n = self.levels(names.select("block", F.col("start").alias("node"), F.lit(self.automaton.initial).alias("state"), mask.alias("mask")).groupBy(*key).agg(F.bit_or("mask").alias("mask")), "mask", key)
        depth = 0
        while not self.ended(depth, n):
            new = self.adj.expand(frontier, self.delta).groupBy("block", F.col("next").alias("node"), F.col("to").alias("state")).agg(F.bit_or("mask").alias("mask"))
            old = seen.all().groupBy(*key).agg(F.bit_or("mask").alias("old"))
            fresh = new.join(old, key, "left").withColumn("mask", F.col("mask").bitwiseAND(F.bitwise_not(F.coalesce("old", F.lit(0).cast("long"))))).filter("mask <> 0").select(*key, "mask")
            frontier, n = self.counted(seen.add(fresh))
            depth += 1
        ends = self.final(seen.all()).groupBy("block", "node").agg(F.bit_or("mask").alias("mask")).join(names, "block").filter(F.call_function("getbit", F.col("mask"), F.col("bit")) == 1)
        out = ends.select("start", F.col("node").alias("end"))
        return out.select(F.col("end").alias("start"), F.col("start").alias("end")) if self.backward else out

    # -- walks ------------------------------------------------------------------
    def any_shortest(self) -> DataFrame:
        """One shortest walk for each pair, the one with the smallest edges: a key keeps its smallest path of its first round."""
        seen, frontier, n = self.levels(self.first(), "any", KEY)
        depth, answers, pair = 0, None, ["start", "node"]
        while True:
            best = self.final(frontier).groupBy(*pair).agg(F.min(F.struct("eids", "nodes")).alias("p")).select(*pair, "p.eids", "p.nodes")
            if answers is None:
                answers = Levels(best, "any_answers", pair, self.buckets)
            else:
                answers.add(best.join(answers.all().select(*pair), pair, "left_anti"))
            if self.ended(depth, n) or self.target is not None and self.limit is None and self._settled(answers):
                break
            cand = self.step(frontier).groupBy(*KEY).agg(F.min(F.struct("eids", "nodes")).alias("p")).select(*KEY, "p.eids", "p.nodes")
            frontier, n = self.counted(seen.add(cand.join(seen.all().select(*KEY), KEY, "left_anti")))
            depth += 1
        return self.out(answers.all())

    def _settled(self, answers: Levels) -> bool:
        """Both ends given and the answer is there: later rounds can add nothing."""
        return answers.all().limit(1).count() > 0 and self.seeds.limit(2).count() == 1

    def explored(self, groups: int) -> tuple[dict, dict]:
        """Levels of product keys with all their predecessors: a key enters a level if it was in fewer than groups levels before.
        groups = 1 is the graph of all shortest walks."""
        cap = F.lit((self.limit or (1 << 40)) + 1).cast("long")
        seen, frontier, n = self.levels(self.first().select(*KEY, F.lit(1).cast("long").alias("cnt")), "all", KEY)
        depth, levels, pred, back = 0, {0: frontier}, {}, None
        while not self.ended(depth, n):
            cand = self.adj.expand(frontier, self.delta).select("start", F.col("next").alias("node"), F.col("to").alias("state"), F.col("node").alias("p_node"), F.col("state").alias("p_state"), "eid", F.col("cnt").alias("p_cnt"))
            if groups == 1:
                cand = cand.join(seen.all().select(*KEY), KEY, "left_anti")
            else:
                full = seen.all().groupBy(*KEY).agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= groups)
                cand = cand.join(full, KEY, "left_anti")
            depth += 1
            if back is None:
                back = Levels(cand, "all_pred", KEY, self.buckets)
            else:
                back.add(cand)
            pred[depth] = back.at(depth - 1)
            self.metrics["pred_rows"] += pred[depth].count()
            frontier, n = self.counted(seen.add(pred[depth].groupBy(*KEY).agg(F.least(F.sum("p_cnt"), cap).alias("cnt"))))
            levels[depth] = frontier
        return levels, pred

    def _by_level(self, groups: int) -> DataFrame:
        levels, pred = self.explored(groups)
        # A node's answer lengths, over all final states, are ranked; the first ones count.
        ends = None
        for d, f in levels.items():
            e = self.final(f).select("start", "node", F.lit(d).alias("length")).distinct()
            ends = e if ends is None else ends.unionByName(e)
        rank = F.dense_rank().over(Window.partitionBy("start", "node").orderBy("length"))
        ends = settle(ends.withColumn("g", rank).filter(F.col("g") <= groups), "all-ends")
        counts = {r["length"] for r in ends.select("length").distinct().collect()}  # as many rows as rounds
        answers = {d: self.final(levels[d]).join(ends.filter(F.col("length") == d).select("start", "node"), ["start", "node"], "left_semi") for d in counts}
        if not answers:
            return self.turned(self._none())
        kinds = (self.node, self.eid)
        if self.limit is None:
            return self.turned(enumeration.all_paths(answers, pred, self.backward, kinds))
        return self.turned(enumeration.some_paths(answers, pred, self.limit, self.backward, kinds))

    def _none(self) -> DataFrame:
        return self.first().filter("false").select("start", F.col("node").alias("end"), F.lit(0).alias("length"), "nodes", "eids")

    def all_shortest(self) -> DataFrame:
        return self._by_level(1)

    def shortest_k_groups(self, k: int) -> DataFrame:
        return self._by_level(k)

    def shortest_k(self, k: int) -> DataFrame:
        """k shortest walks for each pair, by (length, edges): a key passes on its k smallest paths of a round while it has had fewer
        than k in the rounds before; a prefix of one of the k best can always be one of the k best of its key."""
        seen, frontier, n = self.levels(self.first(), "k", KEY)
        answers, depth, pair = None, 0, ["start", "node"]
        while True:
            found = self.final(frontier).select(*pair, "eids", "nodes")
            before = None if answers is None else answers.all().groupBy(*pair).agg(F.count(F.lit(1)).alias("before"))
            found = found.withColumn("before", F.lit(0)) if before is None else found.join(before, pair, "left")
            rank = F.row_number().over(Window.partitionBy(*pair).orderBy("eids"))
            found = found.withColumn("r", rank).filter(F.col("r") <= k - F.coalesce("before", F.lit(0))).select(*pair, "eids", "nodes")
            if answers is None:
                answers = Levels(found, "k_answers", pair, self.buckets)
            else:
                answers.add(found)
            if self.ended(depth, n):
                break
            total = seen.all().groupBy(*KEY).agg(F.count(F.lit(1)).alias("had"))
            cand = self.step(frontier).join(total, KEY, "left").filter(F.coalesce("had", F.lit(0)) < k)
            rank = F.row_number().over(Window.partitionBy(*KEY).orderBy("eids"))
            cand = cand.withColumn("r", rank).filter(F.col("r") <= k - F.coalesce("had", F.lit(0))).select(*KEY, "eids", "nodes")
            frontier, n = self.counted(seen.add(cand))
            depth += 1
        return self.out(answers.all())

    # -- trails, simple and acyclic paths ---------------------------------------
    def alive(self) -> DataFrame | None:
        """(node, state) from which a final state can be reached, of those that the starts reach: the dead-end filter. Both searches
        keep to what the starts reach, so a query from one start looks at its own part of the graph only. None where the
        filter can't pay: an expression of bounded length without a given end has as many rounds as the filter itself."""
        if self.target is None and self.automaton.is_acyclic():
            return None
        key, depth = ["node", "state"], 0
        reached, frontier, n = self.levels(self.first().select(*key).distinct(), "reached", key)
        while not self.ended(depth, n):
            new = self.adj.expand(frontier, self.delta).select(F.col("next").alias("node"), F.col("to").alias("state")).distinct()
            frontier, n = self.counted(reached.add(new.join(reached.all(), key, "left_anti")))
            depth += 1
        alive, frontier, n = self.levels(self.final(reached.all()), "alive", key)
        while n:
            new = self.adj.back(frontier, self.delta).select(F.col("prev").alias("node"), F.col("from").alias("state")).distinct()
            new = new.join(reached.all(), key, "left_semi").join(alive.all(), key, "left_anti")
            frontier, n = self.counted(alive.add(new))
        return alive.all()

    def extended(self, frontier: DataFrame, restrictor: str, alive: DataFrame | None) -> DataFrame:
        """Path rows one edge on, as far as the restrictor allows and answers can be reached."""
        e = self.adj.expand(frontier, self.delta).filter(product.valid(restrictor))
        long = lambda a, x: product.lengthened(F.col(a), F.col(x), self.backward)
        cand = e.select("start", F.col("next").alias("node"), F.col("to").alias("state"), long("eids", "eid").alias("eids"), long("nodes", "next").alias("nodes"))
        cand = cand if alive is None else cand.join(alive, ["node", "state"], "left_semi")
        return cand.select(*KEY, "eids", "nodes")

    def restricted(self, mode: PathMode) -> DataFrame:
        """Paths of a restrictor: rows carry their edges and nodes, invalid extensions and dead ends are dropped each round."""
        alive = self.alive()
        start = self.first()
        if alive is not None:
            start = start.join(alive, ["node", "state"], "left_semi")
        frontier, n = self.counted(settle(start.select(*KEY, "eids", "nodes"), "restricted"))
        answers, depth, found_n, pair = None, 0, 0, ["start", "node"]
        while True:
            found = self._selected(self.final(frontier).select(*pair, "eids", "nodes"), answers, mode)
            if answers is None:
                answers = Levels(found, "restricted_answers", pair, self.buckets)
            else:
                answers.add(found)
            if self.limit is not None:
                found_n += answers.at(answers.depth).count()
                if found_n >= self.limit:
                    break
            if self.ended(depth, n):
                break
            frontier, n = self.counted(settle(self.extended(frontier, mode.restrictor, alive), "restricted"))
            depth += 1
        out = self.out(answers.all())
        return out if self.limit is None else out.limit(self.limit)

    def _selected(self, found: DataFrame, answers: Levels | None, mode: PathMode) -> DataFrame:
        """Of this round's answers those that the selector takes."""
        pair = ["start", "node"]
        if mode.selector == "ALL":
            return found
        had = None
        if answers is not None:
            a = answers.all().withColumn("length", F.size("eids"))
            had = a.groupBy(*pair).agg(F.count(F.lit(1)).alias("paths"), F.count_distinct("length").alias("groups"))
        if mode.selector == "ALL SHORTEST":
            return found if had is None else found.join(had, pair, "left_anti")
        if mode.selector == "SHORTEST K GROUPS":
            return found if had is None else found.join(had.filter(F.col("groups") >= mode.k), pair, "left_anti")
        k = mode.k if mode.selector in ("ANY K", "SHORTEST K") else 1
        rank = F.row_number().over(Window.partitionBy(*pair).orderBy("eids"))
        if had is None:
            return found.withColumn("r", rank).filter(F.col("r") <= k).drop("r")
        return found.join(had, pair, "left").withColumn("r", rank).filter(F.col("r") <= k - F.coalesce("paths", F.lit(0))).select("start", "node", "eids", "nodes")

    # -- by mode ----------------------------------------------------------------
    def run(self, mode: PathMode) -> DataFrame:
        if mode.restrictor != "WALK":
            return self.restricted(mode)
        if mode.selector in ("ANY", "ANY SHORTEST"):
            out = self.any_shortest()
        elif mode.selector == "ALL SHORTEST":
            return self.all_shortest()
        elif mode.selector == "SHORTEST K GROUPS":
            return self.shortest_k_groups(mode.k)
        else:
            out = self.shortest_k(mode.k)
        return out if self.limit is None else out.limit(self.limit)
