"""The path engine: worked examples, the definition by brute force, identities, automata, measures, streams."""

from __future__ import annotations

import itertools
import random
import re

import pytest
from pyspark.sql import functions as F

from pathweave import automaton, baselines, engine, metrics, modes, oracles, query, regex, workloads
from pathweave.automaton import glushkov, thompson
from pathweave.functions import paths as P
from pathweave.graph import GraphError, PathGraph
from pathweave.modes import ALL_MODES, PathMode, PathModeError, parse_mode
from pathweave.operators import condensed, local, product, rounds, seeds, waves
from pathweave.sources import catalog, readers
from pathweave.sqlapi import Engine

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def ex(spark):
    return catalog.example(spark).cached()


def found(r) -> set:
    return {(x["start"], x["end"], x["length"], tuple(x["eids"])) for x in r.df.collect()}


def edges(r) -> set:
    return {tuple(x["eids"]) for x in r.df.collect()}


E = lambda *names: {tuple(n.split(",")) for n in names}


# ------------------------------------------------------------------ worked examples
@pytest.mark.parametrize("strategy", ["local", "rounds"])
def test_worked_examples(ex, strategy):
    go = lambda mode, p, s, e=None, k=None: edges(engine.paths(ex, mode, p, s, e, k=k, strategy=strategy))
    three = E("e3,e5,e11", "e3,e6,e10", "e4,e7,e10")
    two = E("e4,e12,e5,e11", "e4,e12,e6,e10")
    assert go("ALL SHORTEST WALK", "follows*/works", "Joe") == three
    assert go("SIMPLE", "follows*/works", "Joe") == three | two
    assert go("SHORTEST 2 GROUPS WALK", "follows*/works", "Joe") == three | two
    assert len(go("TRAIL", "follows*/works", "Joe")) == 10
    assert go("SIMPLE", "follows+/lives", "John") == E("e1,e3,e5,e9", "e1,e4,e12,e5,e9")
    assert go("ANY SHORTEST WALK", "follows+/lives", "John") == E("e1,e2,e8")


def test_more_worked_examples(ex):
    assert edges(engine.paths(ex, "SIMPLE", "follows+", "Joe", "Lily")) == E("e4")
    assert edges(engine.paths(ex, "TRAIL", "follows+", "Joe", "Lily")) == E("e4", "e2,e1,e4")
    assert len(edges(engine.paths(ex, "SIMPLE", "follows+/works", "Joe"))) == 5
    r = edges(engine.paths(ex, "ALL SHORTEST WALK", "follows/follows/follows", "Joe"))
    assert E("e2,e1,e4", "e2,e1,e3") <= r
    six = edges(engine.paths(ex, "SHORTEST 6 WALK", "follows*/works", "Joe"))
    assert sorted(map(len, six)) == [3, 3, 3, 4, 4, 5]
    assert engine.paths(ex, "ANY WALK", "follows", "Nobody").df.count() == 0


# ------------------------------------------------------------------ the definition
LETTERS = ("a", "b")
PATTERNS = ("a*", "a+/b?", "(a|b)+", "a*/b*", "(a/b)*", "(a+/b)*", "a{1,3}", "a*/a*", "()", "a/(b|a)/b?", "(a|a/a)*")


def small_graph(seed: int):
    r = random.Random(seed)
    n = r.randint(2, 5)
    return [(r.randrange(n), r.choice(LETTERS), r.randrange(n), i) for i in range(r.randint(1, 8))], list(range(n))


class Table:
    """The search of one start, without Spark."""

    def __init__(self, rows):
        self.adj = local.Adjacency([(s, label, False, d, e) for s, label, d, e in rows])

    def run(self, nodes, mode, pattern, bound, order="bfs", end=None):
        a = glushkov(regex.parse(pattern))
        a = a.unambiguous() if mode.counts_paths else a
        out = set()
        for s in nodes:
            for n, (e, v) in local.Search(self.adj, a, target=end, max_length=bound).paths(s, mode, order):
                assert v[0] == s and v[-1] == n and len(v) == len(e) + 1
                key = (s, n, len(e), e)
                assert key not in out
                out.add(key)
        return out


@pytest.mark.parametrize("seed", range(12))
def test_all_27_modes_against_the_definition(seed):
    rows, nodes = small_graph(seed)
    table = Table(rows)
    for pattern in PATTERNS:
        for base in ALL_MODES:
            for k in (1, 2, 3, 7) if "K" in base.selector.split() else (1,):
                mode = PathMode(base.selector, base.restrictor, k)
                bound = 5 if mode.restrictor == "WALK" else 9
                want = baselines.by_definition(rows, nodes, mode, pattern, bound)
                got = table.run(nodes, mode, pattern, bound)
                assert got == want, (pattern, mode)
    assert len(ALL_MODES) == 27


@pytest.mark.parametrize("seed", range(6))
def test_depth_first_answers(seed):
    rows, nodes = small_graph(seed + 50)
    table = Table(rows)
    for pattern in PATTERNS:
        for r in modes.RESTRICTORS[1:]:
            every = baselines.by_definition(rows, nodes, PathMode("ALL", r), pattern, 9)
            assert table.run(nodes, PathMode("ALL", r), pattern, None, "dfs") == every
            one = table.run(nodes, PathMode("ANY", r), pattern, None, "dfs")
            assert one <= every and {x[:2] for x in one} == {x[:2] for x in every} and len(one) == len({x[:2] for x in every})
            two = table.run(nodes, PathMode("ANY K", r, 2), pattern, None, "dfs")
            assert two <= every
        ends = {x[:2] for x in table.run(nodes, PathMode("ANY SHORTEST", "WALK"), pattern, None)}
        assert {x[:2] for x in table.run(nodes, PathMode("ANY", "WALK"), pattern, None, "dfs")} == ends


@pytest.fixture
def two_partitions(spark):
    spark.conf.set("spark.sql.shuffle.partitions", "2")
    yield
    spark.conf.set("spark.sql.shuffle.partitions", "4")


def as_graph(spark, rows, nodes):
    return PathGraph.of(spark.createDataFrame(rows, "src long, label string, dst long, eid long"), spark.createDataFrame([(n,) for n in nodes], "id long")).cached()


@pytest.fixture(scope="module")
def small(spark):
    rows, nodes = small_graph(3)
    return rows, nodes, as_graph(spark, rows, nodes)


@pytest.mark.parametrize("base", ALL_MODES, ids=str)
def test_rounds_against_the_definition(small, two_partitions, base):
    rows, nodes, g = small
    mode = PathMode(base.selector, base.restrictor, 2 if "K" in base.selector.split() else 1)
    pattern = "(a|b){0,2}" if mode.restrictor == "WALK" else "a*/b*"
    want = baselines.by_definition(rows, nodes, mode, pattern, 9 if mode.restrictor != "WALK" else 2)
    assert found(engine.paths(g, str(mode), pattern, strategy="rounds")) == want


@pytest.mark.parametrize("text", ["ANY SHORTEST WALK", "SHORTEST 2 WALK", "ALL SHORTEST WALK", "TRAIL", "SHORTEST 2 GROUPS ACYCLIC"])
def test_rounds_with_ends_and_limits(spark, two_partitions, text):
    rows, nodes = small_graph(9)
    g, mode, pattern = as_graph(spark, rows, nodes), parse_mode(text), "(a|b){0,3}"
    every = baselines.by_definition(rows, nodes, mode, pattern, 3)
    s, t = sorted(every, key=lambda x: -x[2])[0][:2]
    assert found(engine.paths(g, text, pattern, s, t, strategy="rounds")) == {x for x in every if x[:2] == (s, t)}
    back = engine.paths(g, text, pattern, end=t, strategy="rounds")
    assert back.plan.backward and found(back) == {x for x in every if x[1] == t}
    some = found(engine.paths(g, text, pattern, limit=3, strategy="rounds"))
    assert some <= every and len(some) == min(3, len(every))


@pytest.mark.parametrize("text", ["TRAIL", "ANY SIMPLE", "ANY 2 ACYCLIC"])
def test_waves_against_the_definition(small, two_partitions, text):
    rows, nodes, g = small
    mode = parse_mode(text)
    every = baselines.by_definition(rows, nodes, PathMode("ALL", mode.restrictor), "a*/b*", 9)
    got = found(engine.paths(g, text, "a*/b*", strategy="rounds", order="dfs"))
    pairs = lambda x: {k: min(len(list(v)), {"ALL": 99, "ANY": 1, "ANY K": mode.k}[mode.selector]) for k, v in itertools.groupby(sorted(x), key=lambda y: y[:2])}
    assert got <= every and pairs(got) == pairs(every)


def test_hubs_are_dealt_over_buckets(spark, monkeypatch):
    rows = [(0, "a", i, i) for i in range(1, 3001)] + [(i, "a", 3001, 3000 + i) for i in range(1, 21)]
    g = as_graph(spark, rows, range(3002))
    a = glushkov(regex.parse("a/a"))
    kept = product.stored(g, a)
    assert {r["node"] for r in kept.hubs.collect()} == {0} and kept.edges.select("salt").distinct().count() > 1
    assert engine.paths(g, "TRAIL", "a/a", 0, strategy="rounds").df.count() == 20
    assert engine.endpoints(g, "a{1,2}", 0, strategy="rounds").df.count() == 3001


def test_a_round_moves_neither_edges_nor_visited_keys(spark, small):
    _, _, g = small
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        a = glushkov(regex.parse("a*/b*"))
        r = rounds.Rounds(g, a, seeds.resolve(g, a, product.adjacency(g, a), None))
        seen, frontier, _ = r.levels(r.first().select(*rounds.KEY), "reach", rounds.KEY)
        new = r.adj.expand(frontier, r.delta).select("start", F.col("next").alias("node"), F.col("to").alias("state")).distinct()
        plan = new.join(seen.all(), rounds.KEY, "left_anti")._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    # The frontier goes to the edges, and candidates to the visited keys; nothing else is dealt anew.
    assert plan.count("SortMergeJoin") == 2 and plan.count("Exchange hashpartitioning") == 2 and plan.count("Bucketed: true") >= 2


@pytest.mark.parametrize("how", [{"strategy": "local"}, {"strategy": "rounds"}, {"strategy": "rounds", "order": "dfs"}])
def test_time_outs_are_never_silent(small, how):
    _, _, g = small
    with pytest.raises(Exception, match="PathTimeout|more than 0 s"):
        engine.paths(g, "TRAIL" if "order" in how else "ANY SHORTEST WALK", "a{0,3}", timeout_s=0, **how).df.collect()
    got = metrics.timed(g.edges.sparkSession, lambda: engine.paths(g, "TRAIL", "a{0,3}", timeout_s=0, **how).df)
    assert got["timed_out"] and got["rows"] is None


def test_a_search_without_answers_looks_at_the_clock():
    ring = [(i, "a", (i + d) % 40, 40 * d + i) for i in range(40) for d in (1, 2, 3)]
    adj = local.Adjacency([(s, label, False, d, e) for s, label, d, e in ring])
    with pytest.raises(rounds.PathTimeout):
        list(local.Search(adj, glushkov(regex.parse("a{90}")), target=0, timeout_s=0.2).paths(0, PathMode("ALL", "TRAIL"), "dfs"))


def test_other_types_of_ids_and_other_graphs_in_the_same_worker(spark):
    one = PathGraph.of(spark.createDataFrame([(1.5, "a", 2.5, 1)], "src double, label string, dst double, eid int"))
    two = PathGraph.of(spark.createDataFrame([(1.5, "a", 3.5, 1)], "src double, label string, dst double, eid int"))
    for _ in range(3):
        for g, end in ((one, 2.5), (two, 3.5)):
            assert {(r["start"], r["end"]) for r in engine.paths(g, "ANY WALK", "a").df.collect()} == {(1.5, end)}


def test_reach_has_no_bound_on_rounds(spark, two_partitions):
    g = as_graph(spark, [(i, "a", i + 1, i) for i in range(12)], range(13))
    assert baselines.reach(g, "a*", 0).count() == 13


@pytest.mark.parametrize("strategy", ["local", "rounds"])
def test_searches_from_the_end_give_the_same(ex, strategy):
    for text in ("ALL SHORTEST WALK", "ANY SHORTEST WALK", "SHORTEST 4 WALK", "TRAIL"):
        ahead = {x for x in found(engine.paths(ex, text, "follows*/works", strategy="local")) if x[1] == "ENS"}
        back = engine.paths(ex, text, "follows*/works", end="ENS", strategy=strategy)
        assert back.plan.backward and found(back) == ahead, text
        if strategy == "rounds" and text == "ANY SHORTEST WALK":
            break


def test_two_way_steps_and_wildcards(ex):
    assert edges(engine.paths(ex, "ANY SHORTEST WALK", "works/^works", "Anne", "Jane")) == E("e11,e10")
    assert edges(engine.paths(ex, "TRAIL", "works/^works", "Anne")) == E("e11,e10")  # an edge counts once, whichever way
    assert edges(engine.paths(ex, "SIMPLE", "!(follows|lives)", "Jane")) == E("e10")
    assert edges(engine.paths(ex, "ANY SHORTEST WALK", "./works", "Lily")) == E("e7,e10")


# ------------------------------------------------------------------ identities
def test_identities(spark):
    g = catalog.hop_slice(spark, SF, 2).cached()
    go = lambda m, p="purchase*/click?", **h: found(engine.paths(g, m, p, **h))
    assert go("SHORTEST 1 WALK") == go("ANY SHORTEST WALK")
    assert go("SHORTEST 1 GROUPS WALK") == go("ALL SHORTEST WALK")
    assert {x[:2] for x in go("ANY WALK", order="dfs")} == {(r["start"], r["end"]) for r in engine.endpoints(g, "purchase*/click?").df.collect()}
    t, s, a = go("TRAIL"), go("SIMPLE"), go("ACYCLIC")
    assert a <= s <= t


def test_same_exploration_of_any_and_all_shortest():
    rows, nodes = small_graph(8)
    adj, a = local.Adjacency([(s, label, False, d, e) for s, label, d, e in rows]), glushkov(regex.parse("(a|b)*")).unambiguous()
    for s in nodes:
        one, every = local.Search(adj, a), local.Search(adj, a)
        list(one.any_shortest(s)), list(every.by_level(s, 1))
        assert one.visited == every.visited


# ------------------------------------------------------------------ automata
def words_up_to(n):
    return itertools.chain.from_iterable(itertools.product(LETTERS, repeat=i) for i in range(n + 1))


@pytest.mark.parametrize("pattern", PATTERNS)
def test_automata_agree(pattern):
    node = regex.parse(pattern)
    rx = re.compile(baselines._pattern_text(node, {"a": "a", "b": "b"}))
    g, t = glushkov(node), thompson(node)
    forms = [g, t, g.determinise(), g.determinise().minimise(), g.unambiguous(), g.reverse().reverse()]
    assert forms[2].is_unambiguous() and forms[4].is_unambiguous()
    for w in words_up_to(5):
        want = bool(rx.fullmatch("".join(w)))
        assert [f.accepts(w) for f in forms] == [want] * 6
        assert g.reverse().accepts(w[::-1]) == want


def test_ambiguity():
    assert not glushkov(regex.parse("a*/(b|a)*/a*")).is_unambiguous()
    assert glushkov(regex.parse("a*/b")).is_unambiguous() and glushkov(regex.parse("a{1,4}")).is_unambiguous()
    assert regex.parse("(a*)*") == regex.parse("a*") == regex.parse("(a+|())*")
    # Without determinising, an ambiguous expression yields a path twice.
    table = Table([(0, "a", 1, 0), (1, "a", 2, 1)])
    a = automaton.Automaton(3, 0, frozenset({1, 2}), ((0, ("a", False), 1), (0, ("a", False), 2), (1, ("a", False), 1), (1, ("a", False), 2)))
    twice = list(local.Search(table.adj, a).by_level(0, 1))
    assert len(twice) > len(set(twice))


@pytest.mark.parametrize("bad", ["a//b", "(a", "a)", "a{2,1}", "*", "", "a|", "!(a/b)", "$"])
def test_bad_expressions(bad):
    with pytest.raises(regex.RegexError):
        regex.parse(bad)


def test_modes_and_texts():
    assert str(parse_mode("shortest 3 groups trails")) == "SHORTEST 3 GROUPS TRAIL"
    for bad in ("WALK", "ANY K WALK", "BEST TRAIL", "", "SHORTEST 0 TRAIL"):
        with pytest.raises(PathModeError):
            parse_mode(bad)
    q = query.parse("SHORTEST 2 GROUPS TRAIL ('Joe B') -[follows*/works]-> (?x) LIMIT 5")
    assert (q.start, q.end, q.limit, q.mode.k) == ("Joe B", None, 5, 2)
    assert query.parse("(?x) -[a]-> (7)").end == 7 and query.parse("(?x) -[a]-> (7)").mode is None
    assert query.parse_triple("SELECT ANY SHORTEST WALK ?p WHERE { Joe follows*/works ?x }").start == "Joe"
    with pytest.raises(query.QueryError):
        query.parse("nonsense")


# ------------------------------------------------------------------ graphs and what is around
def test_graph_building(spark, tmp_path):
    t = spark.createDataFrame([("x", "p", "y"), ("x", "p", "y"), ("y", "q", "z")], "s string, p string, o string")
    g = PathGraph.from_triples(t)
    assert g.validate().edges.count() == 2
    with pytest.raises(GraphError):
        engine.paths(g, "TRAIL", "p")
    assert engine.paths(PathGraph.from_triples(t, triple_is_edge=True), "TRAIL", "p/q").df.count() == 1
    with pytest.raises(GraphError):
        PathGraph.of(spark.createDataFrame([("a", "l", "b", 1), ("a", "l", "c", 1)], "src string, label string, dst string, eid long")).validate()
    readers.write_edges(g, str(tmp_path / "e"))
    assert readers.read_edges(spark, str(tmp_path / "e")).edges.count() == 2
    (tmp_path / "t.nt").write_text('<a> <p> <b> .\n<b> <q> "lit" .\nnoise\n')
    assert {(r["src"], r["dst"]) for r in readers.triples_text(spark, str(tmp_path / "t.nt")).edges.collect()} == {("a", "b"), ("b", "lit")}
    ex = catalog.example(spark)
    coded, names = ex.dictionary_encode()
    back = {r["code"]: r["id"] for r in names.collect()}
    assert sorted(back) == list(range(8))
    assert {(back[r["src"]], back[r["dst"]]) for r in coded.edges.collect()} == {(r["src"], r["dst"]) for r in ex.edges.collect()}
    assert ex.packed().filter("src = 'Joe' and label = 'follows'").select(F.size("out")).first()[0] == 3
    assert ex.subgraph(labels=["works"]).edges.count() == 2
    assert ex.two_way().count() == 24 and ex.reverse().edges.filter("src = 'ENS'").count() == 2
    assert [catalog.hop(spark, f"/root/testdata/sf{s}", "follows").median_node() for s in ("0.001", "0.01")] == [9, 140]


def test_next_row_crosses_partitions(spark):
    spark.conf.set("spark.sql.shuffle.partitions", "7")
    try:
        d = spark.range(1000).select(F.col("id").alias("event_id"), (F.col("id") * 7 % 1000).alias("ts"), F.col("id").alias("user_id"), F.lit("x").alias("event_type"))
        e = PathGraph.from_sequence(d, ["ts", "event_id"], "user_id", "event_type", "event_id").edges.collect()
        order = [r["event_id"] for r in d.orderBy("ts", "event_id").collect()]
        assert {(r["src"], r["dst"]) for r in e} == set(zip(order, order[1:]))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")


def test_path_functions(spark):
    d = spark.createDataFrame([([1, 2, 1], [7, 8]), ([1, 2, 1, 2], [7, 8, 7]), ([5], []), ([1, 1], [3]), ([1, 2, 2], [4, 5])], "nodes array<long>, eids array<long>")
    got = d.select(P.is_trail("eids"), P.is_simple("nodes"), P.is_acyclic("nodes")).collect()
    assert [tuple(r) for r in got] == [(True, True, False), (False, False, False), (True, True, True), (True, True, False), (True, False, False)]
    j = spark.createDataFrame([([1, 2], [2, 3])], "a array<long>, b array<long>").select(P.path_concat("a", "b", nodes=True).alias("c"), P.path_reverse("a").alias("r")).first()
    assert j["c"] == [1, 2, 3] and j["r"] == [2, 1]


def test_conditions_of_other_selects_stay_where_they_are(spark, ex):
    e = Engine(spark).register("g", ex)
    spark.createDataFrame([("Joe",), ("Joe",), ("Ann",)], "start string").createOrReplaceTempView("people")
    call = "path_query('g', 'ANY SHORTEST WALK (?x) -[follows*/works]-> (?y)')"
    n = engine.paths(ex, "ANY SHORTEST WALK", "follows*/works").df.count()
    joe = engine.paths(ex, "ANY SHORTEST WALK", "follows*/works", "Joe").df.count()
    assert n > joe > 0
    both = e.sql(f"SELECT count(*) AS c FROM people WHERE start = 'Joe' GROUP BY start UNION ALL SELECT count(*) FROM {call}").collect()
    assert sorted(r["c"] for r in both) == sorted([2, n])
    assert e.sql(f"SELECT count(*) AS c FROM {call} t, people p WHERE p.start = 'Joe'").first()["c"] == 2 * n
    assert e.sql(f"WITH w AS (SELECT * FROM {call}) SELECT count(*) AS c FROM w, people WHERE people.start = 'Ann'").first()["c"] == n
    assert e.sql(f"SELECT count(*) AS c FROM {call} WHERE start = 'Joe' OR start = 'John'").first()["c"] == sum(engine.paths(ex, "ANY SHORTEST WALK", "follows*/works", x).df.count() for x in ("Joe", "John"))
    assert e.sql(f"SELECT count(*) AS c FROM (SELECT * FROM {call} AS t WHERE t.start = 'Joe') UNION ALL SELECT count(*) FROM {call}").collect()[1]["c"] == n
    assert Engine._pushed("SELECT * FROM ", " t WHERE t.start = 'Joe' AND length < 3 ORDER BY 1") == {"start": "Joe", "length": 2}
    assert Engine._pushed("SELECT * FROM a, ", " WHERE start = 'Joe'") == {} and Engine._pushed("SELECT * FROM ", " WHERE start = 'Joe' OR length < 2") == {}


def test_results(spark, ex):
    r = engine.paths(ex, "TRAIL", "follows*/works", "Joe")
    assert P.unnest_path(r.df).count() == sum(x["length"] for x in r.df.collect())
    words = {tuple(x["labels"]) for x in P.path_labels(r.df, ex.edges).collect()}
    assert all(w[-1] == "works" and set(w[:-1]) == {"follows"} for w in words)
    assert len(list(r.stream(4))) == 4 and r.top(1, groups=True).count() == 3 and r.top(2).count() == 2
    assert "unambiguous" in r.plan.explain()
    assert r.grouped().count() == 10
    e = Engine(spark).register("g", ex)
    out = e.sql("SELECT `end`, length FROM path_query('g', 'ALL SHORTEST WALK (?x) -[follows*/works]-> (?y)') WHERE start = 'Joe' AND length <= 3")
    assert out.count() == 3
    P.register_udtf(spark)
    assert spark.sql("SELECT * FROM unnest_path(array('x', 'y'))").count() == 2


# ------------------------------------------------------------------ strategies and measures
def test_diamond_measures(spark):
    g = catalog.diamond(spark, 6)
    r = engine.paths(g, "ALL SHORTEST WALK", "a*", 0, 18, strategy="rounds", limit=10)
    assert r.df.count() == 10 and r.metrics()["pred_rows"] == 24
    adj = local.Adjacency([(x["src"], x["label"], False, x["dst"], x["eid"]) for x in catalog.diamond(spark, 40).edges.collect()])
    s = local.Search(adj, glushkov(regex.parse("a*")), target=120, limit=1000)
    got = list(s.paths(0, PathMode("ALL SHORTEST", "WALK")))
    assert len(set(got)) == 1000 and s.pred_rows == 160
    assert len(list(local.Search(adj, glushkov(regex.parse("a*")), target=120, limit=1).paths(0, PathMode("ANY", "TRAIL"), "dfs"))) == 1


def test_waves_and_masks(spark, ex):
    a = glushkov(regex.parse("follows*/works")).unambiguous()
    start = seeds.resolve(ex, a, product.adjacency(ex, a), "Joe")
    out = waves.run(ex, a, start, parse_mode("TRAIL"), chunk=2)
    assert len({tuple(x["eids"]) for x in out.collect()}) == 10
    r = rounds.Rounds(ex, a, seeds.resolve(ex, a, product.adjacency(ex, a), None))
    assert {tuple(x) for x in r.endpoints_by_mask().collect()} == {(x["start"], x["end"]) for x in engine.endpoints(ex, "follows*/works").df.collect()}


def test_timing(spark):
    r = metrics.timed(spark, lambda: spark.range(10).toDF("x"))
    assert r["rows"] == 10 and not r["timed_out"]
    s = metrics.spread(spark, [("TRAIL", "p", 1.0, False), ("TRAIL", "q", 3.0, True)]).first()
    assert s["mean_s"] == 2.0 and s["timeouts"] == 1


def test_pattern_workload(spark):
    out = workloads.patterns(spark, SF, ["ENDPOINTS", "ANY SHORTEST WALK"], only=["p09", "p16a"]).collect()
    assert {r["queries"] for r in out} == {2} and sum(r["timeouts"] for r in out) == 0


def test_stream_edges(spark):
    from pathweave.queries import QUERIES

    assert QUERIES["stream_edges_batch_equal"](spark, SF).count() == 0


def test_incremental_endpoints(spark, ex):
    from pathweave.streaming.edges import IncrementalEndpoints

    inc = IncrementalEndpoints(spark, "follows*/works", spark.createDataFrame([("Joe",), ("John",)], "start string"))
    rows = sorted(catalog.EXAMPLE, key=lambda e: e[3])
    for i in range(0, 12, 6):
        inc(spark.createDataFrame(rows[i : i + 6], "src string, label string, dst string, eid string"), i)
    want = {(r["start"], r["end"]) for r in engine.endpoints(ex, "follows*/works").df.collect() if r["start"] in ("Joe", "John")}
    assert {(r["start"], r["end"]) for r in inc.endpoints().collect()} == want


def test_every_query_has_sql_or_a_reason():
    from pathweave.queries import QUERIES, SQL

    assert set(QUERIES) - set(SQL) == {"stream_edges_batch_equal"}
    assert oracles.endpoints("star", "placed/contains", "C:1").startswith("WITH RECURSIVE")


def test_condensed_endpoints(spark):
    """By classes as by rounds, none of which is run."""
    r = random.Random(0)
    rows = [(r.randrange(9), r.choice(LETTERS), r.randrange(9), i) for i in range(14)]
    g = PathGraph.of(spark.createDataFrame(rows, "src long, label string, dst long, eid long"))
    for pattern in ("a/b*", "^a/(b/a)*"):
        a = glushkov(regex.parse(pattern))
        by_mask = rounds.Rounds(g, a, seeds.resolve(g, a, product.adjacency(g, a), None))
        got = by_mask.endpoints_by_mask().collect()
        assert by_mask.metrics["rounds"] == 0
        want = {tuple(x) for x in engine.endpoints(g, pattern, strategy="rounds").df.collect()}
        assert len(got) == len(want) and {tuple(x) for x in got} == want


def test_condensed_chain_without_rounds(spark):
    n = 600
    g = PathGraph.of(spark.createDataFrame([(i, "a", (i + 1) % n, i) for i in range(n)], "src long, label string, dst long, eid long"))
    a = glushkov(regex.parse("a*"))
    r = rounds.Rounds(g, a, seeds.resolve(g, a, product.adjacency(g, a), None))
    assert r.endpoints_by_mask().count() == n * n and r.metrics["rounds"] == 0


def test_condensed_masks_in_blocks(spark, monkeypatch):
    """Masks that don't fit a worker at once are made block by block, not by rounds."""
    monkeypatch.setattr(condensed, "MASKS", 100)
    r = random.Random(1)
    rows = [(r.randrange(60), r.choice(LETTERS), r.randrange(60), i) for i in range(150)]
    g = PathGraph.of(spark.createDataFrame(rows, "src long, label string, dst long, eid long"))
    a = glushkov(regex.parse("a/b*"))
    by_mask = rounds.Rounds(g, a, seeds.resolve(g, a, product.adjacency(g, a), None))
    got = by_mask.endpoints_by_mask().collect()
    assert by_mask.metrics["rounds"] == 0
    want = {tuple(x) for x in engine.endpoints(g, "a/b*").df.collect()}
    assert len(got) == len(want) > 100 and {tuple(x) for x in got} == want


def test_condensed_answer_is_written_small(spark, tmp_path):
    """Pairs of many ends come by rectangles, so that a written answer takes a small part of a byte a pair."""
    starts, ends = 40, 30_000
    rows = [(i, "a", -1, i) for i in range(starts)] + [(-1, "b", 1000 + i, starts + i) for i in range(ends)]
    g = PathGraph.of(spark.createDataFrame(rows, "src long, label string, dst long, eid long"))
    a = glushkov(regex.parse("a/b"))
    r = rounds.Rounds(g, a, seeds.resolve(g, a, product.adjacency(g, a), None))
    r.endpoints_by_mask().write.parquet(f"{tmp_path}/pairs")
    got = spark.read.parquet(f"{tmp_path}/pairs")
    assert got.count() == got.distinct().count() == starts * ends and got.filter("start between 0 and 39 and end >= 1000").count() == starts * ends
    assert sum(p.stat().st_size for p in (tmp_path / "pairs").glob("*.parquet")) < starts * ends


def test_free_ends_by_class(spark):
    """An expression of bounded length with both ends free: no table of pairs before the answer."""
    r = random.Random(3)
    rows = [(r.randrange(9), r.choice(LETTERS), r.randrange(9), i) for i in range(20)]
    g = PathGraph.of(spark.createDataFrame(rows, "src long, label string, dst long, eid long"))
    for pattern in ("a/^b", "(a/b)?", "(a|b)/a?/^b"):
        found = engine.endpoints(g, pattern, local_edges=0)
        got = [tuple(x) for x in found.df.collect()]
        assert found.metrics()["visited_rows"] == 0
        assert len(got) == len(set(got)) and set(got) == {tuple(x) for x in engine.endpoints(g, pattern).df.collect()}


def test_free_ends_of_one_common_target(spark):
    """Pages that share a target meet as one class, not as pairs."""
    rows = [(f"g{i}", "links", "t", f"l{i}") for i in range(300)] + [(f"g{i}", "on", f"h{i % 3}", f"o{i}") for i in range(300)]
    g = PathGraph.of(spark.createDataFrame(rows, "src string, label string, dst string, eid string"))
    found = engine.endpoints(g, "links/^links/on", local_edges=0)
    assert found.metrics()["visited_rows"] == 0 and found.plan.strategy == "rounds"
    assert {tuple(x) for x in found.df.collect()} == {(f"g{i}", f"h{h}") for i in range(300) for h in range(3)} and found.df.count() == 900


def test_packed_adjacency(spark):
    """Packed arrays hand out what lists do; local search by name holds more edges than it did."""
    import numpy as np

    from pathweave.plans import planner

    r = random.Random(5)
    rows = [(r.randrange(6), r.choice(LETTERS), False, r.randrange(6), i) for i in range(30)]
    listed, syms = local.Adjacency(rows), [("a", False), ("b", False)]
    packed = local.Packed(syms, *(np.array(x) for x in zip(*((syms.index((x[1], x[2])), x[0], x[3], x[4]) for x in rows))))
    assert all(list(packed.at(n, s)) == list(listed.at(n, s)) for n in range(8) for s in [*syms, ("c", False)])
    assert sorted(packed.items()) == sorted(listed.items())
    g = PathGraph.of(spark.range(planner.LOCAL_EDGES + 1).selectExpr("id % 1000 src", "'a' label", "(id + 1) % 1000 dst", "id eid"))
    assert engine.endpoints(g, "a{1,3}", 5, strategy="local").df.count() == 3
    with pytest.raises(GraphError):
        engine.endpoints(g, "a{1,3}", 5, strategy="local", local_edges=10)


def test_stream_pieces_over_batches(spark, tmp_path):
    """Spans of several batches, in a sink that isn't the driver's memory, are the whole sequence."""
    from pathweave.streaming import edges as S

    e, src = catalog.read(spark, SF, "events"), str(tmp_path / "in")
    early = e.orderBy("ts", "event_id").limit(20)
    early.coalesce(1).write.parquet(src)
    q = S.sequence_pieces(S.events(spark, src), 86_400).writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "log")).start()
    q.processAllAvailable()
    e.join(early.select("event_id"), "event_id", "left_anti").select(*e.columns).coalesce(1).write.mode("append").parquet(src)
    q.processAllAvailable()
    q.stop()
    got = S.joined(spark.read.schema(S.PIECES).parquet(str(tmp_path / "out"))).collect()
    want = catalog.hop(spark, SF).edges.select("src", "label", "dst", "eid").collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, want))


def test_all_trails_go_depth_first_over_many_tasks(spark):
    """All restricted paths in workers' memory: one path is held, not a level, and starts don't stay in one task."""
    rows = [(i % 40, "a", (i * 7 + 1) % 40, i) for i in range(60)]
    g = PathGraph.of(spark.createDataFrame(rows, "src long, label string, dst long, eid long"))
    found = engine.paths(g, "TRAIL", "a{1,3}")
    assert found.plan.order == "dfs" and engine.paths(g, "TRAIL", "a{1,3}", order="bfs").plan.order == "bfs"
    assert found.df.select("start").distinct().count() > 8
    assert len({r["p"] for r in found.df.selectExpr("spark_partition_id() p").distinct().collect()}) > 8
    got = [tuple(r["eids"]) for r in found.df.collect()]
    assert len(got) == len(set(got)) and set(got) == {tuple(r["eids"]) for r in engine.paths(g, "TRAIL", "a{1,3}", order="bfs").df.collect()}
