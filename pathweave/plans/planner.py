"""Direction, start set, order and storage of a search, chosen from the query and from counts."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from pathweave import automaton, regex
from pathweave.automaton import Automaton
from pathweave.graph import GraphError, PathGraph
from pathweave.modes import PathMode
from pathweave.operators import local, product, rounds, seeds, waves
from pathweave.query import PathQuery
from pathweave.result import Result

#: Live edges up to which each worker may hold the graph.
LOCAL_EDGES = 400_000
#: The same where local search is asked for by name and ids are integers, so that edges are packed.
PACKED_EDGES = 4_000_000


@dataclass
class PathPlan:
    query: PathQuery
    automaton: Automaton
    backward: bool
    strategy: str  # rounds, local
    order: str  # bfs, dfs
    edges: int | None

    def explain(self) -> str:
        q = self.query
        ends = f"{'one start' if q.start is not None else 'all starts'}, {'one end' if q.end is not None else 'all ends'}"
        return "\n".join(
            [
                f"mode      {q.mode or 'ENDPOINTS'}",
                f"ends      {ends}; search {'from the end, over turned edges' if self.backward else 'from the start'}",
                f"automaton {self.automaton.size} states, {len(self.automaton.delta)} moves, {'unambiguous' if self.automaton.is_unambiguous() else 'ambiguous'}",
                f"labels    {', '.join(('^' if i else '') + label for label, i in self.automaton.alphabet())}",
                f"strategy  {self.strategy}, {self.order}" + (f", {self.edges} live edges in memory" if self.edges is not None else ""),
            ]
        )


def compiled(g: PathGraph, q: PathQuery) -> Automaton:
    pattern = q.pattern if not isinstance(q.pattern, str) else regex.parse(q.pattern)
    if any(isinstance(s, regex.AnyLabel) for s in regex.symbols(pattern)):
        pattern = regex.simplify(regex.resolve(pattern, g.label_names()))
    a = automaton.glushkov(pattern)
    return a.unambiguous() if q.mode is not None and q.mode.counts_paths else a


def order_of(mode: PathMode | None, limit: int | None, asked: str | None) -> str:
    """Depth first where one deep answer should not cost all shallower levels; lengths need breadth first."""
    if mode is None or mode.selector not in ("ANY", "ALL", "ANY K"):
        return "bfs"
    if asked:
        return asked
    return "dfs" if mode.restrictor != "WALK" and mode.selector == "ALL" and limit is not None else "bfs"


def run(g: PathGraph, q: PathQuery, strategy: str = "auto", order: str | None = None, starts: DataFrame | None = None, local_edges: int | None = None) -> Result:
    """The answers of a query. strategy: rounds (joins over the cluster), local (workers hold the live edges), or auto: local
    if the live edges are few enough. starts: a DataFrame of start nodes instead of one constant."""
    if q.mode is not None and q.mode.restrictor == "TRAIL" and not g.triple_is_edge:
        raise GraphError("triples have no edges of their own; TRAIL needs triple_is_edge=True")
    a = compiled(g, q)
    backward = q.start is None and starts is None and q.end is not None
    if backward:
        a = a.reverse()
        if q.mode is not None and q.mode.counts_paths:
            a = a.unambiguous()
    first, target = (q.end, None) if backward else (q.start if starts is None else starts, q.end)
    if local_edges is None:
        local_edges = PACKED_EDGES if strategy == "local" and local.whole_ids(g) else LOCAL_EDGES
    adj = product.adjacency(g, a, backward)
    rows = local.rows_of(g, a, local_edges, backward) if strategy in ("auto", "local") else None
    if strategy == "local" and rows is None:
        raise GraphError(f"more than {local_edges} live edges: too many for local search")
    chosen = "rounds" if rows is None else "local"
    by = order_of(q.mode, q.limit, order)
    if rows is None and q.mode is not None and q.mode.restrictor == "WALK":
        by = "bfs"  # rounds find a shortest walk, which is a walk
    if rows is not None and order is None and q.mode is not None and q.mode.restrictor != "WALK" and q.mode.selector == "ALL":
        by = "dfs"  # every path is wanted, so one in memory does; no level has to be held
    plan = PathPlan(q, a, backward, chosen, by, None if rows is None else rows.edges)
    start = seeds.resolve(g, a, adj, first, backward)
    if rows is not None:
        out = local.run(g, a, rows, start, q.mode, plan.order, backward, target, q.max_length, q.limit, q.timeout_s)
        return Result(out, plan, {"live_edges": float(rows.edges)})
    if q.mode is not None and plan.order == "dfs" and q.mode.restrictor != "WALK":
        return Result(waves.run(g, a, start, q.mode, backward, target, q.max_length, q.limit, timeout_s=q.timeout_s), plan, {})
    r = rounds.Rounds(g, a, start, backward, target, q.max_length, q.limit, q.timeout_s)
    if q.mode is None and q.start is None and q.end is None and starts is None and q.max_length is None and a.is_acyclic():
        out = r.endpoints_by_class()
    else:
        out = r.endpoints() if q.mode is None else r.run(q.mode)
    return Result(out if q.limit is None or q.mode is not None else out.limit(q.limit), plan, r.metrics)
