"""Searches of one start at a time over a packed adjacency in the memory of each worker.

For graphs whose live edges stay under a checked bound the edges are broadcast, as arrays where ids are integers (a compressed
row form: edges sorted by move and node), and each start is searched in a task of its own batch: breadth-first in levels, or depth-first with an explicit
stack of iterators. Generators hand out answers as they are found, so a limit stops the search."""

from __future__ import annotations

import itertools
import time
import uuid
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from pathweave.automaton import Automaton
from pathweave.graph import PathGraph
from pathweave.modes import PathMode
from pathweave.operators import product
from pathweave.operators.rounds import PathTimeout

_HELD: dict = {}
#: Edges up to which a graph with missing integer ids is held, as lists.
LISTED = 400_000
#: Tasks over which the starts of restricted paths are dealt.
STARTS = 64


class Adjacency:
    """node -> (label, inverse) -> its (edge, next) in the order of edges."""

    def __init__(self, rows: list[tuple]):
        self.out: dict = defaultdict(lambda: defaultdict(list))
        for node, label, inverse, nxt, eid in sorted(rows, key=lambda r: r[4]):
            self.out[node][label, inverse].append((eid, nxt))

    def at(self, node, sym) -> list:
        out = self.out.get(node)
        return out.get(sym, ()) if out else ()

    def items(self) -> Iterator[tuple]:
        """(node, move, its edges)."""
        return ((node, sym, edges) for node, out in self.out.items() for sym, edges in out.items())


class Packed:
    """The same over integer ids as arrays: edges sorted by move, node and edge, and for each move the places where nodes begin.
    Lists of visited nodes are kept while they have few edges together."""

    KEPT = 400_000

    def __init__(self, syms: list[tuple], move: np.ndarray, node: np.ndarray, nxt: np.ndarray, eid: np.ndarray):
        order = np.lexsort((eid, node, move))
        move, node = move[order], node[order]
        self.nxt, self.eid, self.by = nxt[order], eid[order], {}
        for i, sym in enumerate(syms):
            lo, hi = np.searchsorted(move, [i, i + 1]).tolist()
            names, first = np.unique(node[lo:hi], return_index=True)
            self.by[sym] = names, np.append(first + lo, hi)
        self.held, self.size = {}, 0

    def __getstate__(self) -> dict:
        return self.__dict__ | {"held": {}, "size": 0}

    def at(self, node, sym) -> list:
        got = self.held.get((node, sym))
        if got is not None:
            return got
        names, places = self.by.get(sym, (np.zeros(0, np.int64), None))
        i = int(np.searchsorted(names, node))
        if i == len(names) or names[i] != node:
            return ()
        lo, hi = int(places[i]), int(places[i + 1])
        if self.size > self.KEPT:
            self.held, self.size = {}, 0
        self.held[node, sym] = got = list(zip(self.eid[lo:hi].tolist(), self.nxt[lo:hi].tolist()))
        self.size += hi - lo
        return got

    def items(self) -> Iterator[tuple]:
        for sym, (names, places) in self.by.items():
            for node, lo, hi in zip(names.tolist(), places[:-1].tolist(), places[1:].tolist()):
                yield node, sym, list(zip(self.eid[lo:hi].tolist(), self.nxt[lo:hi].tolist()))


class Search:
    def __init__(self, adj: Adjacency, a: Automaton, backward: bool = False, target=None, max_length: int | None = None, limit: int | None = None, timeout_s: float | None = None):
        self.adj, self.a, self.backward, self.target, self.max_length, self.limit = adj, a, backward, target, max_length, limit
        self.moves: dict = defaultdict(list)
        for q, (label, inverse), r in a.delta:
            self.moves[q].append(((label, inverse ^ backward), r))
        self.visited, self.pred_rows = 0, 0
        self.timeout_s, self.began, self.ticks = timeout_s, time.monotonic(), 0

    # -- steps ------------------------------------------------------------------
    def check(self) -> None:
        """The clock runs from when the search was made; it is looked at every so many steps, answers or not."""
        if self.timeout_s is not None and self.ticks % 256 == 0 and time.monotonic() - self.began >= self.timeout_s:
            raise PathTimeout(f"PathTimeout: more than {self.timeout_s} s")
        self.ticks += 1

    def steps(self, node, state) -> Iterator[tuple]:
        self.check()
        for sym, to in self.moves[state]:
            for eid, nxt in self.adj.at(node, sym):
                yield eid, nxt, to

    def longer(self, path: tuple, item) -> tuple:
        return (item, *path) if self.backward else (*path, item)

    def answers(self, node, state) -> bool:
        return state in self.a.finals and (self.target is None or node == self.target)

    def deep(self, depth: int) -> bool:
        return self.max_length is not None and depth >= self.max_length

    # -- walks ------------------------------------------------------------------
    def endpoints(self, start) -> Iterator:
        level, seen, done, depth = [(start, self.a.initial)], {(start, self.a.initial)}, set(), 0
        while level:
            for node, state in level:
                if node not in done and self.answers(node, state):
                    done.add(node)
                    yield node
            if self.deep(depth):
                return
            nxt = []
            for key in level:
                for _, n, q in self.steps(*key):
                    if (n, q) not in seen:
                        seen.add((n, q))
                        nxt.append((n, q))
            level, depth = nxt, depth + 1
            self.visited = len(seen)

    def any_shortest(self, start) -> Iterator:
        level = {(start, self.a.initial): ((), (start,))}
        seen, done, depth = set(level), set(), 0
        while level:
            best: dict = {}
            for (node, state), path in level.items():
                if node not in done and self.answers(node, state) and (node not in best or path < best[node]):
                    best[node] = path
            for node, path in best.items():
                done.add(node)
                yield node, path
            if self.deep(depth) or self.target is not None and self.target in done:
                return
            nxt: dict = {}
            for (node, state), (eids, nodes) in level.items():
                for eid, n, q in self.steps(node, state):
                    if (n, q) not in seen:
                        path = self.longer(eids, eid)
                        if (n, q) not in nxt or path < nxt[n, q][0]:
                            nxt[n, q] = (path, self.longer(nodes, n))
            seen |= nxt.keys()
            level, depth = nxt, depth + 1
            self.visited = len(seen)

    def any_walk_deep(self, start) -> Iterator:
        """Depth first: a witness of each pair without the levels in between."""
        key = (start, self.a.initial)
        seen, done, eids, nodes = {key}, set(), [], [start]
        stack = [self.steps(*key)]
        if self.answers(*key):
            done.add(start)
            yield start, ((), (start,))
        while stack:
            move = next(stack[-1], None) if not self.deep(len(eids)) else None
            if move is None:
                stack.pop()
                nodes.pop()
                if eids:
                    eids.pop()
                continue
            eid, n, q = move
            if (n, q) in seen:
                continue
            seen.add((n, q))
            eids.append(eid)
            nodes.append(n)
            stack.append(self.steps(n, q))
            if n not in done and self.answers(n, q):
                done.add(n)
                yield n, self._path(eids, nodes)
        self.visited = len(seen)

    def _path(self, eids: list, nodes: list) -> tuple:
        return (tuple(reversed(eids)), tuple(reversed(nodes))) if self.backward else (tuple(eids), tuple(nodes))

    def by_level(self, start, groups: int) -> Iterator:
        """All paths of the first so many lengths of each pair: levels of keys with all predecessors, then walks back through them."""
        first = (start, self.a.initial)
        level, had, pred, depth = {first: None}, {first: 1}, [{}], 0
        lengths: dict = defaultdict(set)
        while level:
            for node, state in level:
                if self.answers(node, state) and (depth in lengths[node] or len(lengths[node]) < groups):
                    lengths[node].add(depth)
                    yield from ((node, p) for p in self._back(pred, depth, (node, state)))
            if self.deep(depth):
                return
            nxt: dict = {}
            for key in level:
                for eid, n, q in self.steps(*key):
                    if had.get((n, q), 0) < groups:
                        nxt.setdefault((n, q), []).append((key, eid))
            for key in nxt:
                had[key] = had.get(key, 0) + 1
            self.pred_rows += sum(map(len, nxt.values()))
            pred.append(nxt)
            level, depth = nxt, depth + 1
            self.visited = len(had)

    def _back(self, pred: list, depth: int, key: tuple) -> Iterator:
        """Every path to a key of a level, each in time of its length."""
        eids, nodes, stack = [], [key[0]], [iter(pred[depth].get(key, ()))] if depth else []
        if not depth:
            yield (), (key[0],)
            return
        while stack:
            step = next(stack[-1], None)
            if step is None:
                stack.pop()
                nodes.pop()
                if eids:
                    eids.pop()
                continue
            (node, state), eid = step
            d = depth - len(stack)
            eids.append(eid)
            nodes.append(node)
            if d == 0:
                # Collected from the end; a backward search's end is the query's start.
                yield (tuple(eids), tuple(nodes)) if self.backward else (tuple(reversed(eids)), tuple(reversed(nodes)))
                eids.pop()
                nodes.pop()
            else:
                stack.append(iter(pred[d][node, state]))

    def shortest_k(self, start, k: int) -> Iterator:
        level = {(start, self.a.initial): [((), (start,))]}
        had: dict = defaultdict(int)
        had[start, self.a.initial] = 1
        got: dict = defaultdict(int)
        depth = 0
        while level:
            found: dict = defaultdict(list)
            for (node, state), paths in level.items():
                if got[node] < k and self.answers(node, state):
                    found[node] += paths
            for node, paths in found.items():
                for p in sorted(paths)[: k - got[node]]:
                    got[node] += 1
                    yield node, p
            if self.deep(depth) or self.target is not None and got[self.target] >= k:
                return
            cand: dict = defaultdict(list)
            for (node, state), paths in level.items():
                for eid, n, q in self.steps(node, state):
                    if had[n, q] < k:
                        cand[n, q] += [(self.longer(e, eid), self.longer(v, n)) for e, v in paths]
            level = {key: sorted(paths)[: k - had[key]] for key, paths in cand.items()}
            for key, paths in level.items():
                had[key] += len(paths)
            depth += 1
            self.visited = len(had)

    # -- trails, simple and acyclic paths ---------------------------------------
    def alive(self) -> set:
        """Keys from which an answer can be reached, by one search from the ends over the turned adjacency."""
        key = ("alive", self.target)
        kept = getattr(self, "_alive", {})
        if key in kept:
            return kept[key]
        back: dict = defaultdict(list)
        nodes = set()
        by_sym: dict = defaultdict(list)
        for node, sym, edges in self.adj.items():
            nodes.add(node)
            for _, n in edges:
                nodes.add(n)
                by_sym[sym].append((node, n))
        for q, moves in list(self.moves.items()):
            for sym, r in moves:
                for node, n in by_sym[sym]:
                    back[n, r].append((node, q))
        if self.target is not None:
            nodes = {self.target}
        todo = [(n, q) for n in nodes for q in self.a.finals]
        seen = set(todo)
        while todo:
            for prev in back.get(todo.pop(), ()):
                if prev not in seen:
                    seen.add(prev)
                    todo.append(prev)
        self._alive = {key: seen}
        return seen

    def may(self, restrictor: str, start, node, eids, nodes, eid, n) -> bool:
        if restrictor == "TRAIL":
            return eid not in eids
        if restrictor == "ACYCLIC":
            return n not in nodes
        return not (eids and node == start) and (n not in nodes or n == start)

    def wide(self, start, restrictor: str) -> Iterator:
        """Breadth first: (depth, node, path) of every answer path, level by level."""
        alive = self.alive()
        first = (start, self.a.initial)
        level, depth = [(*first, (), (start,))] if first in alive or self.a.accepts_empty() else [], 0
        while level:
            for node, state, eids, nodes in level:
                if self.answers(node, state):
                    yield depth, node, (eids, nodes)
            yield depth, None, None
            if self.deep(depth):
                return
            level = [(n, q, self.longer(eids, eid), self.longer(nodes, n)) for node, state, eids, nodes in level for eid, n, q in self.steps(node, state) if (n, q) in alive and self.may(restrictor, start, node, eids, nodes, eid, n)]
            self.visited += len(level)
            depth += 1

    def deep_first(self, start, restrictor: str) -> Iterator:
        """Depth first: every answer path, with one path in memory."""
        alive, key = self.alive(), (start, self.a.initial)
        if self.answers(*key):
            yield start, ((), (start,))
        eids, nodes, states, stack = [], [start], [key[1]], [self.steps(*key)]
        e_set, n_count = set(), defaultdict(int)
        n_count[start] = 1
        while stack:
            move = next(stack[-1], None) if not self.deep(len(eids)) else None
            if move is None:
                stack.pop()
                n_count[nodes.pop()] -= 1
                if eids:
                    e_set.discard(eids.pop())
                continue
            eid, n, q = move
            if (n, q) not in alive:
                continue
            if restrictor == "TRAIL":
                ok = eid not in e_set
            elif restrictor == "ACYCLIC":
                ok = not n_count[n]
            else:
                ok = not (eids and nodes[-1] == start) and (not n_count[n] or n == start)
            if not ok:
                continue
            eids.append(eid)
            nodes.append(n)
            e_set.add(eid)
            n_count[n] += 1
            stack.append(self.steps(n, q))
            self.visited += 1
            if self.answers(n, q):
                yield n, self._path(eids, nodes)

    def restricted(self, start, mode: PathMode, order: str) -> Iterator:
        wanted = None
        if mode.selector in ("ANY", "ANY SHORTEST"):
            # No restricted answer lacks a walk: once each walk's end is answered there is nothing more to find.
            wanted = set(self.endpoints(start))
        if order == "dfs" and mode.selector in ("ALL", "ANY", "ANY K"):
            got: dict = defaultdict(int)
            most = {"ALL": None, "ANY": 1, "ANY K": mode.k}[mode.selector]
            for node, path in self.deep_first(start, mode.restrictor):
                if most is None or got[node] < most:
                    got[node] += 1
                    yield node, path
                    if wanted is not None:
                        wanted.discard(node)
                        if not wanted:
                            return
            return
        lengths, got, held = defaultdict(set), defaultdict(int), defaultdict(list)
        for depth, node, path in self.wide(start, mode.restrictor):
            if node is not None and mode.selector == "ALL":
                yield node, path
            elif node is not None and mode.selector in ("ALL SHORTEST", "SHORTEST K GROUPS"):
                most = 1 if mode.selector == "ALL SHORTEST" else mode.k
                if depth in lengths[node] or len(lengths[node]) < most:
                    lengths[node].add(depth)
                    yield node, path
            elif node is not None:
                held[node].append(path)
            else:
                most = mode.k if "K" in mode.selector.split() else 1
                for n, paths in held.items():
                    for p in sorted(paths)[: most - got[n]]:
                        got[n] += 1
                        yield n, p
                held.clear()
                if wanted is not None and wanted <= got.keys():
                    return

    def paths(self, start, mode: PathMode, order: str = "bfs") -> Iterator:
        if mode.restrictor != "WALK":
            found = self.restricted(start, mode, order)
        elif mode.selector == "ANY" and order == "dfs":
            found = self.any_walk_deep(start)
        elif mode.selector in ("ANY", "ANY SHORTEST"):
            found = self.any_shortest(start)
        elif mode.selector == "ALL SHORTEST":
            found = self.by_level(start, 1)
        elif mode.selector == "SHORTEST K GROUPS":
            found = self.by_level(start, mode.k)
        else:
            found = self.shortest_k(start, mode.k)
        return itertools.islice(found, self.limit)


def whole_ids(g: PathGraph) -> bool:
    """Whether nodes and edges have integer ids."""
    return all(d.schema[c].dataType.typeName() in ("long", "integer", "short", "byte") for d, c in ((g.edges, "src"), (g.edges, "dst"), (g.edges, "eid")))


def _packed(adj: DataFrame, syms: tuple) -> Packed | None:
    """The edges as arrays; None if an id is missing."""
    move = F.lit(-1)
    for i, (label, inverse) in enumerate(syms):
        move = F.when((F.col("label") == label) & (F.col("inverse") == inverse), i).otherwise(move)
    t = adj.select(move.cast("byte").alias("move") if len(syms) < 128 else move.alias("move"), "node", "next", "eid").toArrow()
    if any(t[c].null_count for c in t.column_names):
        return None
    return Packed(list(syms), *(t[c].to_numpy() for c in t.column_names))


def rows_of(g: PathGraph, a: Automaton, most: int, backward: bool = False) -> Held | None:
    """The live edges, if there are at most so many, broadcast once for a graph and its labels."""
    adj = product.adjacency(g, a, backward)
    key = ("held", tuple(sorted({(s[0], s[1] ^ backward) for _, s, _ in a.delta})))
    if key not in g.kept:
        n = adj.count()
        if n > most:
            return None
        packed = _packed(adj, key[1]) if whole_ids(g) else None
        if packed is None:
            if whole_ids(g) and n > LISTED:
                return None  # integers with gaps: not packed, and too many for lists
            t = adj.select("node", "label", "inverse", "next", "eid").toPandas()
            packed = list(t.itertuples(index=False, name=None))
        g.kept[key] = Held(uuid.uuid4().hex, n, g.edges.sparkSession.sparkContext.broadcast(packed))
    return g.kept[key] if g.kept[key].edges <= most else None


@dataclass
class Held:
    """A broadcast graph; name tells it from others in a worker that is used again."""

    name: str
    edges: int
    sent: object


def run(g: PathGraph, a: Automaton, held_edges: Held, seeds: DataFrame, mode: PathMode | None, order: str = "bfs", backward: bool = False, target=None, max_length: int | None = None, limit: int | None = None, timeout_s: float | None = None) -> DataFrame:
    """start, end, length, nodes, eids for every start of seeds; mode None: start and end only. timeout_s: seconds that each task's
    searches may take; beyond them the job fails with PathTimeout."""
    node, eid = g.nodes.schema["id"].dataType.simpleString(), g.edges.schema["eid"].dataType.simpleString()
    sent, key = held_edges.sent, held_edges.name
    whole = mode is not None
    schema = f"start {node}, end {node}" + f", length int, nodes array<{node}>, eids array<{eid}>" * whole
    n_type, e_type = (to_arrow_type(d.schema[c].dataType) for d, c in ((g.nodes, "id"), (g.edges, "eid")))

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if key not in _HELD:
            _HELD.clear()
            _HELD[key] = Adjacency(sent.value) if isinstance(sent.value, list) else sent.value
        s = Search(_HELD[key], a, backward, target, max_length, limit, timeout_s)

        def batch(held):
            starts, ends, paths = zip(*held)
            if backward:
                starts, ends = ends, starts
            cols = [pa.array(starts, n_type), pa.array(ends, n_type)]
            if whole:
                cols += [pa.array([len(p[0]) for p in paths], pa.int32()), pa.array([p[1] for p in paths], pa.list_(n_type)), pa.array([p[0] for p in paths], pa.list_(e_type))]
            return pa.RecordBatch.from_arrays(cols, ["start", "end", "length", "nodes", "eids"][: len(cols)])

        for b in batches:
            held = []
            for start in b.column(0).to_pylist():
                found = s.paths(start, mode, order) if whole else ((n, None) for n in s.endpoints(start))
                for end, path in found:
                    held.append((start, end, path))
                    if len(held) >= 5000:
                        yield batch(held)
                        held = []
            if held:
                yield batch(held)

    if mode is not None and mode.restrictor != "WALK":
        # A few starts are small data, but not small work: they aren't left together in a task.
        seeds = seeds.repartition(STARTS, "start")
    out = seeds.select("start").mapInArrow(search, schema)
    return out if limit is None else out.limit(limit)
