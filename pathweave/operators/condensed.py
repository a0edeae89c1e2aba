"""Endpoints by classes of product keys that reach the same ends: what is found once for a class isn't found again for each start,
and pairs are made only where they are handed out."""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from pathweave.automaton import Automaton
from pathweave.operators.product import Stored
from pathweave.storage import settle

#: Product edges that one worker condenses, and steps over components and their edges that it takes for all blocks of ends; beyond
#: either the caller has to search by rounds.
EDGES, STEPS = 4_000_000, 100_000_000
#: Bytes of bit masks that a worker holds at once.
MASKS = 400_000_000
#: Ends in a row of a class, and rows of all classes up to which they are broadcast to the starts.
CHUNK, SENT = 2_000, 1_000
#: Starts and ends of a rectangle, whose pairs are all answers. Few ends come again and again, so the answer's columns are short
#: codes and runs wherever it is written.
WIDE, HIGH = 4_000, 500


def pairs(starts: DataFrame, ends: DataFrame, node: str) -> DataFrame:
    """starts(start, cls) and ends(cls, ends: arrays without repeats), a start's classes without common ends -> (start, end). Only
    starts and classes move; where the classes are few they are broadcast, and a class with many starts is as many tasks as its starts have."""
    if ends.limit(SENT + 1).count() <= SENT:
        ends = F.broadcast(ends)
    return starts.join(ends, "cls").select("start", F.explode("ends").alias("end")).select(F.col("start").cast(node), F.col("end").cast(node))


def products(rects: DataFrame, tasks: int) -> DataFrame:
    """(starts, ends), arrays without repeats -> (start, end) of all pairs of each row, rectangle by rectangle and start by start.
    coalesce moves nothing: it parts the two loops, whose generated code would else hold all pairs of a rectangle at once."""
    lines = rects.repartition(tasks).select(F.explode("starts").alias("start"), "ends").coalesce(tasks)
    return lines.select("start", F.explode("ends").alias("end"))


# ------------------------------------------------------------------ expressions of bounded length, over the cluster
def bounded(adj: Stored, a: Automaton, seeds: DataFrame, backward: bool, node: str) -> DataFrame:
    """(start, end) for an automaton without cycles, from its last states to its first: nodes of a state whose next classes are
    equal are one class, and only one node of a class looks for its ends. Sets of next classes are told apart by their size
    and two sums of 64-bit hashes."""
    steps: dict = {}
    for q, s, r in a.delta:
        steps.setdefault(q, []).append((adj.moves[s[0], s[1] ^ backward], r))
    done: dict = {}

    def solve(q: int) -> tuple[DataFrame | None, DataFrame | None]:
        """(node, cls) and (cls, end) of a state; None for one without moves, whose nodes are their own classes and ends."""
        if q in done:
            return done[q]
        if q not in steps:
            return None, None
        to, held = None, None
        for move, r in steps[q]:
            e = adj.edges.filter(F.col("move") == move).select("node", F.col("next"))
            keys, ends = solve(r)
            if keys is None:
                step = e.select("node", F.col("next").cast("string").alias("child"), F.lit(r).alias("to"), F.col("next").alias("own"))
            else:
                step = e.join(keys.select(F.col("node").alias("next"), F.col("cls").alias("child")), "next").select("node", "child", F.lit(r).alias("to"), F.lit(None).cast(node).alias("own"))
                if held is None or r not in held:
                    held = (held or {}) | {r: ends}
            to = step if to is None else to.unionByName(step)
        if q in a.finals:
            own = adj.edges.filter(F.col("move").isin([m for m, _ in steps[q]])).select("node")
            for p, s, r in a.delta:
                if r == q:
                    own = own.unionByName(adj.edges.filter(F.col("move") == adj.moves[s[0], s[1] ^ backward]).select(F.col("next").alias("node")))
            if q == a.initial:
                own = own.unionByName(seeds.select(F.col("start").alias("node")))
            to = to.unionByName(own.select("node", F.col("node").cast("string").alias("child"), F.lit(-1).alias("to"), F.col("node").alias("own")))
        if q == a.initial:
            to = to.join(seeds.select(F.col("start").alias("node")), "node", "left_semi")
        to = settle(to.distinct(), "classes")
        h = lambda seed: F.sum(F.xxhash64(F.lit(seed), "to", "child").cast("decimal(38,0)"))
        sig = F.concat_ws(":", F.count(F.lit(1)).cast("string"), h(1).cast("string"), h(2).cast("string"))
        keys = settle(to.groupBy("node").agg(sig.alias("cls")), "classes")
        one = keys.groupBy("cls").agg(F.min("node").alias("node"))
        found = one.join(to, "node").select("cls", "child", "to", "own")
        ends = found.filter("own is not null").select("cls", F.col("own").alias("end"))
        for r, e in (held or {}).items():
            ends = ends.unionByName(found.filter((F.col("to") == r) & F.col("own").isNull()).select("cls", "child").join(e.withColumnRenamed("cls", "child"), "child").select("cls", "end"))
        done[q] = keys, settle(ends.distinct(), "class-ends")
        return done[q]

    keys, ends = solve(a.initial)
    if keys is None:
        return seeds.select("start", F.col("start").alias("end")).filter(F.lit(a.initial in a.finals))
    part = F.pmod(F.xxhash64("end"), F.ceil(F.col("n") / CHUNK))
    sizes = ends.groupBy("cls").agg(F.count(F.lit(1)).alias("n"))
    chunks = settle(ends.join(sizes, "cls").groupBy("cls", part.alias("part")).agg(F.collect_list("end").alias("ends")).select("cls", "ends"), "class-ends")
    return pairs(keys.select(F.col("node").alias("start"), "cls"), chunks, node)


# ------------------------------------------------------------------ any expression, in one worker
def components(n: int, src: np.ndarray, dst: np.ndarray) -> tuple[list, list]:
    """(component of each key, members of each component) of strong connection; a component comes after all that it reaches."""
    order = np.argsort(src, kind="stable")
    at, to = np.searchsorted(src[order], np.arange(n + 1)).tolist(), dst[order].tolist()
    index, low, comp, out, held, clock = [0] * n, [0] * n, [-1] * n, [], [], 0
    place = at[:]
    for root in range(n):
        if index[root]:
            continue
        work = [root]
        while work:
            v = work[-1]
            if not index[v]:
                clock += 1
                index[v] = low[v] = clock
                held.append(v)
            i, deeper = place[v], False
            while i < at[v + 1]:
                w = to[i]
                i += 1
                if not index[w]:
                    work.append(w)
                    deeper = True
                    i -= 1  # looked at again for its low
                    break
                if comp[w] < 0 and low[w] < low[v]:
                    low[v] = low[w]
            place[v] = i
            if deeper:
                continue
            work.pop()
            if low[v] == index[v]:
                members = []
                while True:
                    w = held.pop()
                    comp[w] = len(out)
                    members.append(w)
                    if w == v:
                        break
                out.append(members)
    return comp, out


def within(adj: Stored, a: Automaton, seeds: DataFrame, backward: bool, target, node: str) -> DataFrame | None:
    """(start, end) of any automaton where its product has few enough edges: a worker condenses the product, a component's ends are
    a bit mask made of those of the components that it reaches, and starts with equal masks are one class. Masks are made of one block
    of ends after another, so their bytes are bounded, and a start has a class in each block that it reaches. A class is handed on
    as rectangles of its starts and ends, dealt over tasks. None beyond the bounds."""
    live = adj.edges.select("node", "move", "next").filter("node is not null").distinct()
    live = settle(live, "condensed")
    by_move = {r["move"]: r["count"] for r in live.groupBy("move").count().collect()}  # as many rows as moves
    delta = [(q, adj.moves[s[0], s[1] ^ backward], r) for q, s, r in a.delta]
    if sum(by_move.get(m, 0) for _, m, _ in delta) > EDGES:
        return None
    rows = live.unionByName(seeds.select(F.col("start").alias("node"), F.lit(-1).alias("move"), F.col("start").alias("next")))
    kind, size, first, finals = to_arrow_type(live.schema["node"].dataType), a.size, a.initial, sorted(a.finals)
    most, steps = MASKS, STEPS

    def condense(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = list(batches)
        if not got:
            return
        t = pa.Table.from_batches(got)
        coded = pc.dictionary_encode(pa.concat_arrays([*t["node"].chunks, *t["next"].chunks]), null_encoding="encode")
        names, codes, move = coded.dictionary, coded.indices.to_numpy().astype(np.int64), t["move"].to_numpy()
        src, dst, n = codes[: len(move)], codes[len(move) :], len(names)
        starts = src[move == -1]
        e = [(src[move == m] * size + q, dst[move == m] * size + r) for q, m, r in delta]
        s, d = (np.concatenate(x) if e else np.zeros(0, np.int64) for x in (zip(*e) if e else ((), ())))
        # Only keys that a start reaches: the search goes on from known ones, level by level.
        order = np.argsort(s, kind="stable")
        s, d = s[order], d[order]
        at = np.searchsorted(s, np.arange(n * size + 1))
        seen = np.zeros(n * size, bool)
        todo = np.unique(starts * size + first)
        seen[todo] = True
        while len(todo):
            count = at[todo + 1] - at[todo]
            places = np.repeat(at[todo] - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(count.sum())
            todo = np.unique(d[places])
            todo = todo[~seen[todo]]
            seen[todo] = True
        keep = np.flatnonzero(seen)
        small = np.cumsum(seen) - 1
        used = seen[s]
        s, d = small[s[used]], small[d[used]]
        comp, members = components(len(keep), s, d)
        comp = np.array(comp, np.int64)
        c_src, c_dst = comp[s], comp[d]
        cross = c_src != c_dst
        cross = np.unique(np.stack([c_src[cross], c_dst[cross]]), axis=1) if cross.any() else np.zeros((2, 0), np.int64)
        c_at, c_to = np.searchsorted(cross[0], np.arange(len(members) + 1)).tolist(), cross[1].tolist()
        wanted = None if target is None else pc.index(names, pa.scalar(target, kind)).as_py()
        node_of, final = (keep // size).tolist(), np.isin(keep % size, finals).tolist()
        # A bit for each end, in the order of components: a mask is as long as its highest bit only.
        bit, ends = {}, []
        for m in members:
            for k in m:
                if final[k] and node_of[k] not in bit and (wanted is None or node_of[k] == wanted):
                    bit[node_of[k]] = len(ends)
                    ends.append(node_of[k])
        ends = np.array(ends, np.int64)
        bits_of = [sorted(bit[node_of[k]] for k in m if final[k] and node_of[k] in bit) for m in members]
        per = max(8, min(len(ends) + 7, most * 8 // max(1, len(members))) // 8 * 8)
        if -(-len(ends) // per) * (len(members) + len(c_to)) > steps:
            yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.list_(kind))] * 2, ["starts", "ends"])
            return
        firsts = np.unique(starts)
        of = comp[small[firsts * size + first]].tolist()
        for lo in range(0, len(ends), per):
            masks, pool = [], {}
            for c, own in enumerate(bits_of):
                own, mask = own[bisect_left(own, lo) : bisect_left(own, lo + per)], 0
                if own:
                    flat = np.zeros(own[-1] - lo + 1, np.uint8)
                    flat[np.array(own) - lo] = 1
                    mask = int.from_bytes(np.packbits(flat, bitorder="little").tobytes(), "little")
                for w in c_to[c_at[c] : c_at[c + 1]]:
                    mask |= masks[w]
                masks.append(pool.setdefault(mask, mask))
            cls: dict = {}
            there = [(cls.setdefault(masks[c], len(cls)), x) for c, x in zip(of, firsts.tolist()) if masks[c]]
            if not there:
                continue
            c, x = np.array(there, np.int64).T
            x, cuts = x[np.argsort(c, kind="stable")], np.concatenate([[0], np.cumsum(np.bincount(c))]).tolist()
            for mask, c in cls.items():
                bits = np.unpackbits(np.frombuffer(mask.to_bytes(per // 8, "little"), np.uint8), bitorder="little")
                own = names.take(pa.array(np.sort(ends[lo + np.flatnonzero(bits)])))
                mine = names.take(pa.array(x[cuts[c] : cuts[c + 1]]))
                high = HIGH if len(mine) > CHUNK // HIGH else CHUNK
                lists = pa.ListArray.from_arrays(pa.array(np.append(np.arange(0, len(own), high), len(own)), pa.int32()), own)
                for j in range(0, len(mine), WIDE):
                    some = mine.slice(j, WIDE)
                    for i in range(0, len(lists), 50):
                        few = lists.slice(i, 50)
                        flat = some.take(pa.array(np.tile(np.arange(len(some)), len(few))))
                        cuts_of = pa.array(np.arange(len(few) + 1) * len(some), pa.int32())
                        yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(cuts_of, flat), few], ["starts", "ends"])

    out = settle(rows.repartition(1).mapInArrow(condense, f"starts array<{node}>, ends array<{node}>"), "condensed")
    if out.filter("ends is null").limit(1).count():
        return None
    return products(out, max(1, int(live.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
