"""Depth-first search in waves: the driver keeps a stack of written frontier chunks (as plans, never rows) and always expands
the deepest. A chunk has a bounded number of rows, so live rows stay under chunk size times depth, and a limit is reached
without the levels in between being complete."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathweave.automaton import Automaton
from pathweave.graph import PathGraph
from pathweave.modes import PathMode
from pathweave.operators.rounds import KEY, Rounds
from pathweave.storage import Levels, settle

CHUNK = 200_000


def run(g: PathGraph, a: Automaton, seeds: DataFrame, mode: PathMode, backward: bool = False, target=None, max_length: int | None = None, limit: int | None = None, chunk: int = CHUNK, timeout_s: float | None = None) -> DataFrame:
    """Paths of a restrictor under no selector, ANY or ANY k, in no particular order."""
    r = Rounds(g, a, seeds, backward, target, max_length, limit, timeout_s)
    alive, first = r.alive(), r.first().select(*KEY, "eids", "nodes")
    stack = [(0, settle(first if alive is None else first.join(alive, ["node", "state"], "left_semi").select(*KEY, "eids", "nodes"), "wave"))]
    answers, total, pair = None, 0, ["start", "node"]
    while stack:
        r.check()
        depth, frontier = stack.pop()
        found = r._selected(r.final(frontier).select(*pair, "eids", "nodes"), answers, mode)
        if answers is None:
            answers = Levels(found, "wave_answers", pair, r.buckets)
        else:
            answers.add(found)
        if limit is not None:
            total += answers.at(answers.depth).count()
            if total >= limit:
                break
        if max_length is not None and depth >= max_length:
            continue
        nxt = settle(r.extended(frontier, mode.restrictor, alive), "wave")
        rows = nxt.count()
        parts = -(-rows // chunk)
        for i in range(parts):
            stack.append((depth + 1, nxt if parts == 1 else nxt.filter(F.pmod(F.xxhash64("start", "eids"), F.lit(parts)) == i)))
    out = r.out(answers.all()) if answers is not None else r.out(r.first().filter("false"))
    return out if limit is None else out.limit(limit)
