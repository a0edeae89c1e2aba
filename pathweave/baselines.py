"""What the methods are compared with: the semantics of other engines, and of the definition itself, as plain Spark."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathweave import automaton, engine, regex
from pathweave.functions import paths as P
from pathweave.graph import PathGraph
from pathweave.modes import PathMode
from pathweave.operators import product, rounds, seeds
from pathweave.result import Result
from pathweave.storage import settle


def _compiled(pattern: str):
    return automaton.glushkov(regex.parse(pattern))


def reach(g: PathGraph, pattern: str, start=None) -> DataFrame:
    """Endpoints only, as engines over triples answer: keys to a fixed point, by set difference instead of an anti-join."""
    a = _compiled(pattern)
    adj, delta = product.adjacency(g, a), product.transitions(g.edges.sparkSession, a)
    seeds = g.nodes if start is None else g.nodes.filter(F.col("id") == F.lit(start))
    seen = settle(seeds.select(F.col("id").alias("start"), F.col("id").alias("node"), F.lit(a.initial).alias("state")), "baseline")
    frontier = seen
    while True:
        new = product.expand(frontier, delta, adj).select("start", F.col("next").alias("node"), F.col("to").alias("state")).exceptAll(seen).distinct()
        new = settle(new.join(seen, ["start", "node", "state"], "left_anti"), "baseline")
        if not new.limit(1).count():
            break  # the fixed point
        seen, frontier = settle(seen.unionByName(new), "baseline"), new
    return seen.filter(F.col("state").isin(list(a.finals))).select("start", F.col("node").alias("end")).distinct()


def bounded_walks(g: PathGraph, pattern: str, start=None, max_length: int = 30) -> DataFrame:
    """Every walk up to a length: what an engine without selectors must cap."""
    a = _compiled(pattern).unambiguous()
    adj = product.adjacency(g, a)
    r = rounds.Rounds(g, a, seeds.resolve(g, a, adj, start), max_length=max_length)
    return _walks(r)


def _walks(r) -> DataFrame:
    frontier = settle(r.first(), "walks")
    levels = [frontier]
    for _ in range(r.max_length):
        frontier = settle(r.step(frontier), "walks")
        if not frontier.limit(1).count():
            break
        levels.append(frontier)
    out = None
    for f in levels:
        found = r.out(r.final(f).select("start", "node", "eids", "nodes"))
        out = found if out is None else out.unionByName(found)
    return out


def enumerate_trails(spark: SparkSession, g: PathGraph, pattern: str, start, max_length: int) -> DataFrame:
    """All trails by a recursive table expression with path arrays, the expression tested on the word of labels at the end:
    no automaton cuts the search short."""
    g.edges.createOrReplaceTempView("__baseline_edges")
    kind = g.nodes.schema["id"].dataType.simpleString()
    eid = g.edges.schema["eid"].dataType.simpleString()
    g.nodes.filter(F.col("id") == F.lit(start).cast(kind)).createOrReplaceTempView("__baseline_starts")
    out = spark.sql(f"""
        WITH RECURSIVE t(start, node, length, nodes, eids, labels) AS (
          SELECT id, id, 0, array(id), cast(array() AS array<{eid}>), cast(array() AS array<string>) FROM __baseline_starts
          UNION ALL
          SELECT t.start, e.dst, t.length + 1, array_append(t.nodes, e.dst), array_append(t.eids, e.eid), array_append(t.labels, e.label)
          FROM t JOIN __baseline_edges e ON e.src = t.node WHERE t.length < {int(max_length)} AND NOT array_contains(t.eids, e.eid)
        ) SELECT start, node AS end, length, nodes, eids, labels FROM t""")
    return out.filter(P.accepts("labels", _compiled(pattern))).drop("labels")


def enumerate_then_filter(g: PathGraph, pattern: str, start=None, max_length: int = 6, all_shortest: bool = True) -> DataFrame:
    """Shortest walks the long way: every walk up to a bound, then the least length by window."""
    w = bounded_walks(g, pattern, start, max_length)
    by = Window.partitionBy("start", "end")
    least = w.withColumn("least", F.min("length").over(by)).filter("length = least").drop("least")
    if all_shortest:
        return least
    return least.withColumn("r", F.row_number().over(by.orderBy("eids"))).filter("r = 1").drop("r")


def per_start_loop(g: PathGraph, mode: str, pattern: str, starts: list, **how) -> DataFrame:
    """One search after the other, for the given starts: what batching of starts saves."""
    out = None
    for s in starts:
        d = engine.paths(g, mode, pattern, s, **how).df
        out = d if out is None else out.unionByName(d)
    return out


def eager_product(g: PathGraph, pattern: str) -> PathGraph:
    """The whole product graph, written: what the lazy step avoids. Its nodes are "node|state"."""
    a = _compiled(pattern)
    adj, delta = product.adjacency(g, a), product.transitions(g.edges.sparkSession, a)
    e = adj.join(F.broadcast(delta), ["label", "inverse"])
    name = lambda n, q: F.concat_ws("|", F.col(n).cast("string"), F.col(q).cast("string"))
    e = e.select(name("node", "state").alias("src"), F.lit("step").alias("label"), name("next", "to").alias("dst"), F.concat_ws("|", F.col("eid").cast("string"), "state", "to").alias("eid"))
    return PathGraph.of(settle(e, "product"))


def eager_reach(g: PathGraph, pattern: str, start) -> DataFrame:
    """Endpoints over the written product."""
    a, p = _compiled(pattern), eager_product(g, pattern)
    r = engine.endpoints(PathGraph.of(p.edges, p.nodes.unionByName(g.edges.sparkSession.createDataFrame([(f"{start}|{a.initial}",)], "id string")).distinct()), "step*", f"{start}|{a.initial}").df
    cut = F.regexp_extract("end", r"^(.*)\|(\d+)$", 2).cast("int")
    kind = g.nodes.schema["id"].dataType
    return r.filter(cut.isin(list(a.finals))).select(F.lit(start).cast(kind).alias("start"), F.regexp_extract("end", r"^(.*)\|(\d+)$", 1).cast(kind).alias("end")).distinct()


def by_definition(edges: list[tuple], nodes: list, mode: PathMode, pattern: str, max_length: int, start=None, end=None) -> set:
    """The definition read literally, on the driver, for tests: all paths up to a length that meet the restrictor and whose word the
    expression accepts (as a regular expression over one letter for each label); then the selector. For modes that leave a
    choice the answer is that of the order by (length, edges)."""
    import re

    letters = {label: chr(0x100 + i) for i, label in enumerate(sorted({e[1] for e in edges}))}
    rx = re.compile(_pattern_text(regex.parse(pattern), letters))
    out: dict = {}
    todo = [((n,), (), "") for n in nodes if start is None or n == start]
    while todo:
        vs, es, word = todo.pop()
        if rx.fullmatch(word) and (end is None or vs[-1] == end):
            out.setdefault((vs[0], vs[-1]), []).append((len(es), es, vs))
        if len(es) == max_length:
            continue
        for s, label, d, e in edges:
            if s != vs[-1]:
                continue
            es2, vs2 = (*es, e), (*vs, d)
            ok = {
                "WALK": True,
                "TRAIL": len(set(es2)) == len(es2),
                "ACYCLIC": len(set(vs2)) == len(vs2),
                "SIMPLE": len(set(vs2)) == len(vs2) or vs2[0] == vs2[-1] and len(set(vs2[1:])) == len(vs2) - 1,
            }[mode.restrictor]
            if ok:
                todo.append((vs2, es2, word + letters[label]))
    picked = set()
    for (s, d), found in out.items():
        found = sorted(found)
        lengths = sorted({f[0] for f in found})
        if mode.selector in ("ANY", "ANY SHORTEST"):
            found = found[:1]
        elif mode.selector == "ALL SHORTEST":
            found = [f for f in found if f[0] == lengths[0]]
        elif mode.selector in ("ANY K", "SHORTEST K"):
            found = found[: mode.k]
        elif mode.selector == "SHORTEST K GROUPS":
            found = [f for f in found if f[0] in lengths[: mode.k]]
        picked |= {(s, d, n, es) for n, es, _ in found}
    return picked


def _pattern_text(p, letters: dict) -> str:
    if isinstance(p, regex.Sym):
        return letters.get(p.label, "￿")
    if isinstance(p, regex.Eps):
        return ""
    if isinstance(p, regex.Star):
        return f"(?:{_pattern_text(p.inner, letters)})*"
    join = "|" if isinstance(p, regex.Alt) else ""
    return "(?:" + join.join(_pattern_text(x, letters) for x in p.parts) + ")"


def shadow(result: Result) -> DataFrame:
    """start, end, length and the path as text: the form in which methods and baselines are compared."""
    return result.df.select("start", "end", "length", P.path_text("eids").alias("path"))
